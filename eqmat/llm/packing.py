"""Best-fit packing by minimum bin slack: each sequence takes the fullest feasible combination of available lengths.

Only the count of pieces of each length matters for the plan, and there are at most ``capacity`` lengths, so the plan
is made on the driver from a histogram of fixed size whatever the corpus holds; rows are then placed by their rank
within their length, which is counted in two steps (within a task, then across tasks) so that a hot length is never
gathered in one place.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from eqmat.llm.pretokens import Generations, byte_slices
from eqmat.storage import saved

CAPACITY, END_ID = 2048, 0
LONGEST_MERGED = 256  # letters of a word that the merger takes; its steps grow with the longest word
_TOKENIZERS: dict[str, tuple] = {}
#: Letters that lower-case one by one and are in composed form: ASCII, Latin-1 and Latin Extended without the dotted I.
_PLAIN = re.compile("[A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u012f\u0131-\u024f]+")
#: ASCII marks that the pattern takes as one run after letters; the apostrophe may begin a suffix.
_MARKS = "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~"


class WordMerger:
    """The merges of a word-end BPE vocabulary, done for many words at once: in each step every word that can still
    merge joins its own best pair."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        vocab, mark = model["vocab"], model["end_of_word_suffix"]
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        keys = np.array([vocab[a] << 20 | vocab[b] for a, b in pairs], np.int64)
        made = np.array([vocab[a + b] for a, b in pairs], np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.rank, self.made = np.append(keys[order], 1 << 62), np.append(order, len(order)).astype(np.int64), made
        self.none = len(order)
        shown = self._byte_letters()
        self.inner = np.array([vocab[c] for c in shown], np.int64)
        self.final = np.array([vocab[c + mark] for c in shown], np.int64)

    @staticmethod
    def _byte_letters() -> list[str]:
        """The printable stand-in of each byte in byte-level vocabularies: itself where it is a visible Latin-1
        character, else the next code point from 256 on."""
        out, spare = [], 256
        for b in range(256):
            if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174:
                out.append(chr(b))
            else:
                out.append(chr(spare))
                spare += 1
        return out

    def _ranks(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        key = a << 20 | b
        at = np.searchsorted(self.keys, key)
        return np.where(self.keys[at] == key, self.rank[at], self.none)

    def encode(self, words: list[str]) -> list[bytes]:
        """Ids of words of plain letters in lower case."""
        coded = [w.encode() for w in words]
        n = np.array([len(w) for w in coded], np.int64)
        if not len(n):
            return []
        stop = np.cumsum(n)
        raw = np.frombuffer(b"".join(coded), np.uint8)
        sym = self.inner[raw]
        sym[stop - 1] = self.final[raw[stop - 1]]
        word = np.repeat(np.arange(len(n)), n)
        rank = np.full(len(sym), self.none, np.int64)
        same = np.flatnonzero(word[1:] == word[:-1])
        rank[same] = self._ranks(sym[same], sym[same + 1])
        ended: list[tuple[np.ndarray, np.ndarray]] = []
        while len(sym):
            first = np.flatnonzero(np.append(True, word[1:] != word[:-1]))
            size = np.diff(np.append(first, len(sym)))
            best = np.minimum.reduceat(rank, first)
            live = best < self.none
            if not live.all():
                done = np.repeat(~live, size)
                ended.append((word[done], sym[done]))
                sym, word, rank = sym[~done], word[~done], rank[~done]
                size, best = size[live], best[live]
                if not len(sym):
                    break
                first = np.append(0, np.cumsum(size)[:-1])
            hit = np.flatnonzero(rank == np.repeat(best, size))
            hit = hit[np.append(True, word[hit][1:] != word[hit][:-1])]  # the leftmost of each word
            sym[hit] = self.made[best]
            stay = np.ones(len(sym), bool)
            stay[hit + 1] = False
            sym, word, rank = sym[stay], word[stay], rank[stay]
            hit -= np.arange(len(hit))  # one symbol has gone from each word before
            right = hit[hit + 1 < len(sym)]
            right = right[word[right] == word[right + 1]]
            rank[hit] = self.none
            rank[right] = self._ranks(sym[right], sym[right + 1])
            left = hit[hit > 0] - 1
            left = left[word[left] == word[left + 1]]
            rank[left] = self._ranks(sym[left], sym[left + 1])
        word, sym = (np.concatenate(x) for x in zip(*ended, strict=True))
        order = np.argsort(word, kind="stable")
        flat = sym[order].astype("<u4").tobytes()
        cuts = [0, *(4 * np.cumsum(np.bincount(word, minlength=len(n)))).tolist()]
        return [flat[a:b] for a, b in zip(cuts, cuts[1:])]


def _tokenizer(path: str):
    """The tokenizer, kept for the life of a Python worker, and its two caches, kept for a task: whole chunks, and words
    below them."""
    if path not in _TOKENIZERS:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        tok = Tokenizer.from_file(path)
        tok.encode_special_tokens = True
        _TOKENIZERS[path] = (tok, WordMerger(path), Generations(250_000), Generations(350_000))
    return _TOKENIZERS[path]


def forget(path: str) -> None:
    """Empty the caches of a tokenizer, whose entries are mostly words of one text or task."""
    for cache in _TOKENIZERS.get(path, ())[2:]:
        cache.clear()


def _encode_words(tok, merger: WordMerger, words: list[str]) -> list[bytes]:
    """Words of plain letters by the merger, whatever else there is, and words of great length, by the tokenizer itself."""
    plain = [len(w) <= LONGEST_MERGED and bool(_PLAIN.fullmatch(w)) for w in words]
    fast = iter(merger.encode([w.lower() for w, p in zip(words, plain, strict=True) if p]))
    slow = iter(tok.encode_batch_fast([w for w, p in zip(words, plain, strict=True) if not p], add_special_tokens=False))
    return [next(fast) if p else np.asarray(next(slow).ids, "<u4").tobytes() for p in plain]


def _odd(text: str) -> bool:
    """Control characters that str.split takes for white space and the tokenizer does not."""
    return "\x1c" in text or "\x1d" in text or "\x1e" in text or "\x1f" in text


def encode_texts(path: str, texts: list[str | None]) -> list[bytes]:
    """Little-endian 32-bit ids of each text, as the tokenizer itself would give them.

    The tokenizer drops white space before it merges, so a text is the sequence of its white-space chunks and each
    chunk can be looked up. Letters with a tail of marks are the sequence of the two.
    """
    tok, merger, chunks, words = _tokenizer(path)
    chunks.turn()
    words.turn()
    split = [[] if not t else None if _odd(t) else t.split() for t in texts]

    def make(missing: list[str]) -> list[bytes]:
        cut = []
        for c in missing:
            body = c.rstrip(_MARKS)
            if body.isalpha() and (low := body.lower()).isalpha():  # lower case can end in a mark of its own
                cut.append((low if body.isascii() else body, c[len(body) :]))
            else:
                cut.append((c, ""))
        flat = [w for pair in cut for w in pair]
        values = words.values(flat, lambda m: _encode_words(tok, merger, m))
        return [a + b for a, b in zip(values[::2], values[1::2], strict=True)]

    out = chunks.joined([s or [] for s in split], make)
    return [_encode_words(tok, merger, [t])[0] if s is None else x for s, t, x in zip(split, texts, out, strict=True)]


PIECES = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("task", pa.int64()), ("nth", pa.int64())])


def _pieces(path: str, capacity: int, end_id: int):
    tail = int(end_id).to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from numbered(batches, TaskContext.get().partitionId())
        finally:
            forget(path)  # an idle worker would keep them beside whatever the executor does next

    def numbered(batches: Iterator[pa.RecordBatch], task: int) -> Iterator[pa.RecordBatch]:
        seen: dict[int, int] = {}
        for batch in batches:
            for part in byte_slices(batch):
                out: list[tuple] = []
                for doc, ids in zip(part.column(0).to_pylist(), encode_texts(path, part.column(1).to_pylist()), strict=True):
                    ids += tail
                    for k, b in enumerate(range(0, len(ids), 4 * capacity)):
                        own = ids[b : b + 4 * capacity]
                        n = len(own) // 4
                        nth = seen.get(n, 0)
                        seen[n] = nth + 1
                        out.append((doc, k, b // 4, n, zlib.crc32(own), task, nth))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), PIECES, strict=True)], schema=PIECES)

    return run


def token_pieces(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """One row per piece of a document's ids, with its rank among the pieces of its length that its task has made."""
    narrow = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return narrow.mapInArrow(_pieces(tokenizer_path, capacity, end_id), "doc_id long, piece int, start long, length long, ids_crc32 long, task long, nth long")


def fullest(counts: dict[int, int], room: int) -> dict[int, int]:
    """How many of each length make the largest sum of at most ``room``, by subset sums on a bitset."""
    mask, reach, steps = (1 << (room + 1)) - 1, 1, []
    for length in sorted((x for x, n in counts.items() if n and x <= room), reverse=True):
        left, unit = min(counts[length], room // length), 1
        while left:
            take = min(unit, left)
            steps.append((length, take, reach))
            reach |= (reach << (length * take)) & mask
            left, unit = left - take, unit * 2
            if reach >> room & 1:
                break
        if reach >> room & 1:
            break
    total, used = reach.bit_length() - 1, {}
    for length, take, before in reversed(steps):
        if not before >> total & 1:
            used[length] = used.get(length, 0) + take
            total -= length * take
    return used


def minimum_slack_plan(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[dict[int, int], int]]:
    """[(length -> times in one sequence, sequences alike)]: the largest length left is placed, the fullest
    combination is added, and the same sequence is repeated as long as the counts allow it."""
    left = {x: n for x, n in counts.items() if n > 0}
    if any(not 0 < x <= capacity for x in left):
        raise ValueError("a length is out of range")
    plan = []
    while left:
        first = max(left)
        left[first] -= 1
        use = fullest(left, capacity - first)
        left[first] += 1
        use[first] = use.get(first, 0) + 1
        times = min(left[x] // k for x, k in use.items())
        plan.append((use, times))
        for x, k in use.items():
            left[x] -= k * times
            if not left[x]:
                del left[x]
    return plan


def _slots(plan: list[tuple[dict[int, int], int]]) -> dict[int, list[np.ndarray]]:
    """length -> columns (first rank, first sequence, times in a sequence, offset of the first), in order of rank."""
    rows: dict[int, list[tuple]] = {}
    given: dict[int, int] = {}
    sequence = 0
    for use, times in plan:
        offset = 0
        for length in sorted(use, reverse=True):
            k = use[length]
            rows.setdefault(length, []).append((given.get(length, 0), sequence, k, offset))
            given[length] = given.get(length, 0) + k * times
            offset += length * k
        sequence += times
    return {x: [np.array(c, np.int64) for c in zip(*r, strict=True)] for x, r in rows.items()}


def _place(slots: dict[int, list[np.ndarray]]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            length, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
            sequence, offset = np.zeros(len(rank), np.int64), np.zeros(len(rank), np.int64)
            for x in np.unique(length):
                at = np.flatnonzero(length == x)
                first, seq, k, off = slots[int(x)]
                j = np.searchsorted(first, rank[at], side="right") - 1
                inside = rank[at] - first[j]
                sequence[at] = seq[j] + inside // k[j]
                offset[at] = off[j] + inside % k[j] * x
            keep = ["doc_id", "piece", "start", "length", "ids_crc32"]
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in keep], pa.array(sequence), pa.array(offset)], names=[*keep, "sequence_id", "offset"])

    return run


def pack(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """Pack the token ids of docs(doc_id, text) into sequences of at most ``capacity``.

    Each document is its ids and then ``end_id``; only longer ones are cut. Returns doc_id, piece, start, length,
    ids_crc32, sequence_id, offset. A null text is an empty one (one piece of length 1), a null doc_id stays null,
    repeated rows are packed each by itself, an empty table gives no rows; other columns are not looked at.
    """
    pieces = saved(token_pieces(docs, tokenizer_path, capacity, end_id), "pieces")
    per_task = saved(pieces.groupBy("task", "length").agg(F.count("*").alias("n")), "lengths")
    counts = {r["length"]: r["n"] for r in per_task.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `capacity` rows
    before = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    offsets = per_task.select("task", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    ranked = pieces.hint("merge").join(offsets, ["task", "length"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("base") + F.col("nth")).alias("rank"))
    # By merge: the offsets grow with the tasks and lengths, and only narrow rows move.
    slots = _slots(minimum_slack_plan(counts, capacity))
    return ranked.mapInArrow(_place(slots), "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
