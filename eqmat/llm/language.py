"""Language identification by a bidirectional gated recurrent network over bytes, trained here in numpy.

Texts are read in windows of 64 bytes that tile the whole text. A forward and a backward pass give two states for
each byte, a linear layer and softmax label every byte, and a document's probabilities are the mean over its bytes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WINDOW, HIDDEN, BLOCK = 64, 8, 4096
NO_LANGUAGE = "und"
_LETTER = regex.compile(r"\p{L}")


def _gate(x: np.ndarray) -> np.ndarray:
    return np.clip(x * np.float32(0.2) + np.float32(0.5), 0, 1)


class ByteGRU:
    """Two gated recurrent layers of ``hidden`` units, one for each direction, and a softmax over the labels."""

    def __init__(self, labels: list[str], hidden: int = HIDDEN, seed: int = 7):
        self.labels, self.h = labels, hidden
        r, h, c = np.random.default_rng(seed), hidden, len(labels)
        self.p = {}
        for d in "fb":
            self.p["E" + d] = r.normal(0, 0.4, (256, 3 * h)).astype(np.float32)
            self.p["U" + d] = r.normal(0, 0.35, (h, 3 * h)).astype(np.float32)
            self.p["W" + d] = r.normal(0, 0.35, (h, c)).astype(np.float32)
        self.p["b"] = np.zeros(c, np.float32)

    def _run(self, x: np.ndarray, d: str, tape: list | None = None) -> np.ndarray:
        """States (T, B, h) for bytes x (B, T); the backward direction reads from the end."""
        h, (table, u) = self.h, (self.p["E" + d], self.p["U" + d])
        b, t = x.shape
        state, out = np.zeros((b, h), np.float32), np.empty((t, b, h), np.float32)
        for k in range(t) if d == "f" else range(t - 1, -1, -1):
            own, rec = table[x[:, k]], state @ u
            zr = _gate(own[:, : 2 * h] + rec[:, : 2 * h])
            z, r = zr[:, :h], zr[:, h:]
            n = np.tanh(own[:, 2 * h :] + r * rec[:, 2 * h :])
            if tape is not None:
                tape.append((k, state, zr, n, rec[:, 2 * h :]))
            state = n + z * (state - n)
            out[k] = state
        return out

    def position_probabilities(self, x: np.ndarray) -> np.ndarray:
        """(T, B, labels) for bytes x (B, T)."""
        s = self._run(x, "f") @ self.p["Wf"] + self._run(x, "b") @ self.p["Wb"] + self.p["b"]
        s -= s.max(axis=2, keepdims=True)
        np.exp(s, out=s)
        s /= s.sum(axis=2, keepdims=True)
        return s

    def gradients(self, x: np.ndarray, y: np.ndarray, mask: np.ndarray) -> tuple[float, dict]:
        """Mean cross entropy over the bytes under mask (B, T), and its gradients through time."""
        h, p, t = self.h, self.p, x.shape[1]
        tapes: dict[str, list] = {"f": [], "b": []}
        states = {d: self._run(x, d, tapes[d]) for d in "fb"}
        s = states["f"] @ p["Wf"] + states["b"] @ p["Wb"] + p["b"]
        s -= s.max(axis=2, keepdims=True)
        s = np.exp(s)
        s /= s.sum(axis=2, keepdims=True)
        weight = (mask.T / max(mask.sum(), 1)).astype(np.float32)
        picked = np.take_along_axis(s, np.broadcast_to(y, (t, len(y)))[:, :, None], 2)[:, :, 0]
        loss = float(-(np.log(np.maximum(picked, 1e-12)) * weight).sum())
        ds = s * weight[:, :, None]
        np.put_along_axis(ds, np.broadcast_to(y, (t, len(y)))[:, :, None], (picked * weight - weight)[:, :, None], 2)
        g = {k: np.zeros_like(v) for k, v in p.items()}
        g["b"] = ds.sum(axis=(0, 1))
        for d in "fb":
            g["W" + d] = np.einsum("tbh,tbc->hc", states[d], ds)
            into = ds @ p["W" + d].T
            u, carry = p["U" + d], np.zeros((len(x), h), np.float32)
            for k, before, zr, n, rec in reversed(tapes[d]):
                up = into[k] + carry
                z, r = zr[:, :h], zr[:, h:]
                dn = up * (1 - z) * (1 - n * n)
                open_ = ((zr > 0) & (zr < 1)) * np.float32(0.2)
                dz = up * (before - n) * open_[:, :h]
                dr = dn * rec * open_[:, h:]
                pre = np.concatenate([dz, dr, dn], axis=1)
                through = np.concatenate([dz, dr, dn * r], axis=1)
                np.add.at(g["E" + d], x[:, k], pre)
                g["U" + d] += before.T @ through
                carry = up * z + through @ u.T
        return loss, g

    def fit(self, x: np.ndarray, y: np.ndarray, mask: np.ndarray, epochs: int = 10, batch: int = 384, rate: float = 0.012, seed: int = 5) -> float:
        """Adam over shuffled batches; returns the last mean loss."""
        r = np.random.default_rng(seed)
        m, v = ({k: np.zeros_like(a) for k, a in self.p.items()} for _ in range(2))
        step, last = 0, 0.0
        for epoch in range(epochs):
            order, losses = r.permutation(len(x)), []
            for at in range(0, len(x), batch):
                i = order[at : at + batch]
                loss, g = self.gradients(x[i], y[i], mask[i])
                losses.append(loss)
                step += 1
                for k, a in self.p.items():
                    grad = np.clip(g[k], -1, 1)
                    m[k] += 0.1 * (grad - m[k])
                    v[k] += 0.005 * (grad * grad - v[k])
                    a -= (rate * 0.8**epoch * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.995**step)) + 1e-8)).astype(np.float32)
            last = float(np.mean(losses))
        return last

    def documents(self, texts: list[str | None]) -> np.ndarray:
        """(documents, labels): mean probabilities over all bytes of each text; zeros for an empty one."""
        coded = [(t or "").encode() for t in texts]
        n = np.array([len(c) for c in coded])
        windows = -(-n // WINDOW)
        doc = np.repeat(np.arange(len(coded)), windows)
        raw = np.zeros((int(windows.sum()), WINDOW), np.uint8)
        filled = np.minimum(WINDOW, np.repeat(n, windows) - WINDOW * (np.arange(len(doc)) - np.repeat(np.cumsum(windows) - windows, windows)))
        inside = np.arange(WINDOW)[None, :] < filled[:, None]
        raw[inside] = np.frombuffer(b"".join(coded), np.uint8)
        total = np.zeros((len(coded), len(self.labels)))
        for at in range(0, len(raw), BLOCK):
            probs = self.position_probabilities(raw[at : at + BLOCK])
            probs *= inside[at : at + BLOCK].T[:, :, None]
            np.add.at(total, doc[at : at + BLOCK], probs.sum(axis=0, dtype=np.float64))
        return total / np.maximum(n, 1)[:, None]


def _training_windows(rows: list[tuple[str, str]], labels: list[str], per_doc: int, seed: int = 3) -> tuple:
    r, at = np.random.default_rng(seed), {c: i for i, c in enumerate(labels)}
    x, y, mask = [], [], []
    for text, lang in rows:
        raw = text.encode()
        for start in r.integers(0, max(len(raw) - WINDOW, 0) + 1, min(per_doc, 1 + len(raw) // WINDOW)):
            own = np.frombuffer(raw[start : start + WINDOW], np.uint8)
            if len(own):
                x.append(np.pad(own, (0, WINDOW - len(own))))
                y.append(at[lang])
                mask.append(np.arange(WINDOW) < len(own))
    return np.array(x, np.uint8).reshape(-1, WINDOW), np.array(y, np.int64), np.array(mask, bool).reshape(-1, WINDOW)


def balanced_sample(rows: DataFrame, label: str, key: str, per_label: int, seed: int = 11) -> DataFrame:
    """About ``per_label`` rows of each label, picked by a hash of the key: a count of labels and one filtered scan."""
    counts = [(r[0], r[1]) for r in rows.groupBy(label).count().collect() if r[0] is not None]
    if not counts:
        return rows.where(F.lit(False))
    shares = F.map_from_arrays(F.array(*(F.lit(value) for value, _ in counts)), F.array(*(F.lit(min(1.0, per_label / n)) for _, n in counts)))
    share = F.element_at(shares, F.col(label))
    return rows.where(F.pmod(F.xxhash64(F.lit(seed), F.col(key)), F.lit(1_000_000)) < share * 1_000_000)


def train(docs: DataFrame, docs_per_label: int = 250, windows_per_doc: int = 6, most_docs: int = 125_000, epochs: int = 10) -> ByteGRU:
    """Fit on a bounded sample of docs(doc_id, text, lang) with a lang: about ``docs_per_label`` documents of each
    language and ``windows_per_doc`` windows of each of them, wherever they stand in the text. Every language is learned:
    where there are so many that this would pass ``most_docs`` in all, each gives fewer documents, though never less
    than about one. Rows of one doc_id (repeated rows, null ids) are picked together and teach one text, the least of
    each language; a language of which the hash picked none gives its least text."""
    known = docs.where("lang is not null and text is not null and length(text) > 0").select("doc_id", "text", "lang")
    langs = [r[0] for r in known.select("lang").distinct().collect()]
    per_label = max(1, min(docs_per_label, most_docs // max(len(langs), 1)))
    picked = balanced_sample(known, "lang", "doc_id", per_label).groupBy("lang", "doc_id").agg(F.min("text").alias("text")).collect() if langs else []
    if missed := set(langs) - {r["lang"] for r in picked}:
        wanted = F.array_contains(F.array(*map(F.lit, sorted(missed))), F.col("lang"))
        picked += known.where(wanted).groupBy("lang").agg(F.min_by("doc_id", "text").alias("doc_id"), F.min("text").alias("text")).collect()
    rows = [(r["text"], r["lang"]) for r in sorted(picked, key=lambda r: (r["doc_id"] is None, r["doc_id"] or 0, r["text"]))]
    model = ByteGRU(sorted({lang for _, lang in rows}) or [NO_LANGUAGE])
    if rows and len(model.labels) > 1:
        model.fit(*_training_windows(rows, model.labels, windows_per_doc), epochs=epochs)
    return model


def predict(docs: DataFrame, model: ByteGRU) -> DataFrame:
    """docs with lang_pred and score added (both replaced if docs has them); texts are read whole.

    lang_pred is ``und`` with score 0 for a text that is null, empty or holds no letter. Ties go to the first label.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(b.schema.get_field_index("text")).to_pylist()
            lang, score = [], []
            for at in range(0, len(texts), 128):
                part = texts[at : at + 128]
                for t, p in zip(part, model.documents(part), strict=True):
                    known = bool(t and _LETTER.search(t))
                    best = int(p.argmax())
                    lang.append(model.labels[best] if known else NO_LANGUAGE)
                    score.append(float(min(max(p[best], 0.0), 1.0)) if known else 0.0)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=[*b.schema.names, "lang_pred", "score"])

    plain = docs.drop("lang_pred", "score")
    schema = plain.schema
    from pyspark.sql import types as T

    out = T.StructType([*schema.fields, T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())])
    return plain.mapInArrow(run, out)


def keep_known(docs: DataFrame, model: ByteGRU, least: float = 0.3) -> DataFrame:
    """The rows of docs whose text has a language that the model gives at least ``least``; columns as they were.

    A text with a letter also stays where the model cannot judge it: where it has learned no language at all (no row had
    a lang to learn from), and where the row's own lang is none of those learned."""
    names = docs.columns
    found = (F.col("lang_pred") != NO_LANGUAGE) & (F.col("score") >= least)
    letter = F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False))
    if model.labels == [NO_LANGUAGE]:
        return docs.where(letter)
    if "lang" in names:
        found = found | (F.coalesce(~F.col("lang").isin(model.labels), F.lit(False)) & letter)
    return predict(docs, model).where(found).select(*names)
