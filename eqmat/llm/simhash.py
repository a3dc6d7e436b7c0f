"""SimHash near-duplicates, linked through a hierarchical index over Gray-ordered fingerprints.

Two fingerprints that differ in at most three of 64 bits agree in one of four 16-bit blocks, so each distinct
fingerprint is sent to four groups and every link is found inside one of them. A group that is too large is dealt
again by four blocks of the 48 bits that are left, and of the 36 and 27 left then, which loses no link for the same reason. Inside a group the
fingerprints are sorted by Gray rank and the bits that neighbours share are factored into upper nodes; a search adds
up differences on the way down and drops a whole subtree once they pass the limit, or once its members and the query
are known to be connected already. So a dense cluster costs little more than its size and is given out as a star.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eqmat.components import connected_components
from eqmat.llm.pretokens import byte_slices
from eqmat.storage import keyed, saved

SEED, SHINGLE, MOST_BITS = 42, 3, 3
FAN, MOST_GROUP, MOST_FRONTIER = 8, 4096, 2_000_000
INDEXED_AT_ONCE = 65_536  # rows of whole groups


def shingle_hashes(text: str | None, size: int = SHINGLE) -> list[int]:
    words = (text or "").encode().lower().split()  # bytes: A-Z only, and exactly the six ASCII white-space characters
    if not words:
        return []
    joined = b" ".join(words)
    if len(words) < size:
        return [xxhash.xxh64_intdigest(joined, SEED)]
    ends = (np.cumsum([len(w) + 1 for w in words]) - 1).tolist()
    starts = [0, *[e + 1 for e in ends[:-size]]]
    digest = xxhash.xxh64_intdigest
    return [digest(joined[a:b], SEED) for a, b in zip(starts, ends[size - 1 :], strict=True)]


def fingerprints(texts: list[str | None], size: int = SHINGLE) -> np.ndarray:
    """64-bit fingerprints: a bit is set when over half of the shingle hashes have it. No words: zero."""
    out = np.zeros(len(texts), np.uint64)
    for k, text in enumerate(texts):
        h = shingle_hashes(text, size)
        if h:
            counts = np.zeros(64, np.int64)
            raw = np.array(h, np.uint64).view(np.uint8).reshape(-1, 8)
            for at in range(0, len(raw), 65_536):
                counts += np.unpackbits(raw[at : at + 65_536], axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
            out[k] = np.packbits(counts * 2 > len(h), bitorder="little").view(np.uint64)[0]
    return out


def gray_rank(f: np.ndarray) -> np.ndarray:
    """Place of a code word in the Gray sequence: each bit is the parity of the bits from the top down to it."""
    b = f.copy()
    for shift in (1, 2, 4, 8, 16, 32):
        b ^= b >> np.uint64(shift)
    return b


class GrayIndex:
    """Levels of nodes over (group, fingerprint) rows in Gray order; a node holds the bits on which all below agree."""

    def __init__(self, groups: np.ndarray, prints: np.ndarray, fan: int = FAN):
        order = np.lexsort((gray_rank(prints), groups))
        self.groups, self.prints = groups[order], prints[order]
        n = len(order)
        full = np.full(n, ~np.uint64(0))
        level = {"value": self.prints, "mask": full, "group": self.groups, "lo": np.arange(n), "hi": np.arange(1, n + 1)}
        self.levels = [level]
        while True:
            g = level["group"]
            fresh = np.append(True, g[1:] != g[:-1])
            if fresh.all():
                break
            first_of = np.flatnonzero(fresh)
            nth = np.arange(len(g)) - np.repeat(first_of, np.diff(np.append(first_of, len(g))))
            start = np.flatnonzero(nth % fan == 0)
            size = np.diff(np.append(start, len(g)))
            differs = level["value"] ^ np.repeat(level["value"][start], size)
            agree = np.bitwise_and.reduceat(level["mask"] & ~differs, start)
            level = {"value": level["value"][start] & agree, "mask": agree, "group": g[start], "lo": level["lo"][start], "hi": level["hi"][start + size - 1], "start": start, "size": size}
            self.levels[-1]["own"] = self.levels[-1]["mask"] & ~np.repeat(agree, size)
            self.levels.append(level)
        self.levels[-1]["own"] = self.levels[-1]["mask"]
        self.root = np.searchsorted(level["group"], self.groups)
        self.comp = np.arange(n)

    def _uniform(self) -> list[np.ndarray]:
        """For each node the component that all its leaves have, or -1."""
        out, low, high = [self.comp], self.comp, self.comp
        for level in self.levels[1:]:
            low, high = np.minimum.reduceat(low, level["start"]), np.maximum.reduceat(high, level["start"])
            out.append(np.where(low == high, low, -1))
        return out

    def _search(self, queries: np.ndarray, most: int, uniform: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray] | None:
        """Pairs (query, leaf) within ``most`` bits and not yet connected; None if the frontier grows too large."""
        q, node = queries, self.root[queries]
        acc = np.zeros(len(q), np.int64)
        for depth in range(len(self.levels) - 1, -1, -1):
            level = self.levels[depth]
            acc = acc + np.bitwise_count((self.prints[q] ^ level["value"][node]) & level["own"][node])
            stay = (acc <= most) & (uniform[depth][node] != self.comp[q])
            q, node, acc = q[stay], node[stay], acc[stay]
            if depth:
                size = level["size"][node]
                if size.sum() > MOST_FRONTIER and len(queries) > 1:
                    return None
                ends = np.cumsum(size)
                inner = np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - size, size)
                q, node, acc = np.repeat(q, size), np.repeat(level["start"][node], size) + inner, np.repeat(acc, size)
        return q, node

    def _union(self, a: np.ndarray, b: np.ndarray) -> None:
        """Smallest member as label, by hooking and pointer jumping."""
        comp = self.comp
        while True:
            x, y = comp[a], comp[b]
            if (x == y).all():
                break
            np.minimum.at(comp, np.maximum(x, y), np.minimum(x, y))
            while True:
                jumped = comp[comp]
                if (jumped == comp).all():
                    break
                comp = jumped
            a, b = a[x != y], b[x != y]
        self.comp = comp

    def connect(self, most: int = MOST_BITS) -> np.ndarray:
        """For each row of self.prints the first row that it is connected to."""
        n = len(self.prints)
        rest = np.ones(n, bool)
        for stride in (4096, 256, 16, 1):  # a few of each region first: later searches skip what is connected
            queries = np.flatnonzero(rest)[::stride]
            rest[queries] = False
            todo = [queries[at : at + 16_384] for at in range(0, len(queries), 16_384)][::-1]
            while todo:
                part = todo.pop()
                found = self._search(part, most, self._uniform())
                if found is None:
                    todo += [part[len(part) // 2 :], part[: len(part) // 2]]
                elif len(found[0]):
                    self._union(*found)
        return self.comp


def _fingerprint_rows(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (part for batch in batches for part in byte_slices(batch)):
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(fingerprints(b.columns[-1].to_pylist(), size).view(np.int64))], names=[*b.schema.names[:-1], "fp"])

    return run


def document_fingerprints(docs: DataFrame, size: int = SHINGLE, *also: str) -> DataFrame:
    """doc_id, the long columns in also, fp (the 64 bits as a signed long). A null text has no words."""
    ids = ["doc_id", *also]
    narrow = docs.select(*[F.col(c).cast("long").alias(c) for c in ids], F.col("text").cast("string").alias("text"))
    return narrow.mapInArrow(_fingerprint_rows(size), ", ".join(f"{c} long" for c in [*ids, "fp"]))


def _whole_groups(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(groups, fingerprints) of rows that come sorted by group: about ``rows`` at a time, never part of a group."""
    held: list[tuple[np.ndarray, np.ndarray]] = []
    n = 0
    for b in batches:
        g, f = b.column(0).to_numpy(), b.column(1).to_numpy()
        if not len(g):
            continue
        if n >= rows:  # the last group goes on for as long as its number comes again
            cut = int(np.searchsorted(g, held[-1][0][-1], side="right"))
            held.append((g[:cut], f[:cut]))
            n += cut
            if cut == len(g):
                continue
            yield tuple(np.concatenate(x) for x in zip(*held, strict=True))
            held, n, g, f = [], 0, g[cut:], f[cut:]
        held.append((g, f))
        n += len(g)
    if held:
        yield tuple(np.concatenate(x) for x in zip(*held, strict=True))


def _stars(most: int, rows: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for groups, prints in _whole_groups(batches, rows):
            index = GrayIndex(groups, prints.view(np.uint64))
            top = index.connect(most)
            at = np.flatnonzero(top != np.arange(len(top)))
            f = index.prints.view(np.int64)
            if len(at):
                yield pa.RecordBatch.from_arrays([pa.array(f[at]), pa.array(f[top[at]])], names=["u", "v"])

    return run


def _dealt(rows: DataFrame, width: int) -> DataFrame:
    """rows(grp, fp, rest) once for each of four blocks of the ``width`` low bits of rest: grp tells the groups so far and
    the bits of the block, rest has the other bits, moved together. Two that meet in a group by chance are none the
    worse for it: every link is decided by the fingerprints."""
    own = width // 4
    out = rows.withColumn("k", F.explode(F.array(*map(F.lit, range(4)))))
    block = F.expr(f"shiftrightunsigned(rest, k * {own}) & {(1 << own) - 1}L")
    low, high = F.expr("rest & (shiftleft(1L, k * %d) - 1)" % own), F.expr(f"case when k = 3 then 0L else shiftleft(shiftrightunsigned(rest, (k + 1) * {own}), k * {own}) end")
    return out.select(F.xxhash64("grp", "k", block).alias("grp"), "fp", (low.bitwiseOR(high)).alias("rest"))


def _grouped(prints: DataFrame) -> DataFrame:
    """grp, fp: four groups for each fingerprint; the rows of groups of over MOST_GROUP are dealt again by the bits that
    are left, three times at most, for fingerprints that agree in a block differ in three bits at most of the others."""
    rows, width, done = _dealt(prints.select(F.lit(0).cast("long").alias("grp"), "fp", F.col("fp").alias("rest")), 64), 48, None
    while True:
        heavy = saved(rows.groupBy("grp").count().where(F.col("count") > MOST_GROUP).select(F.col("grp").alias("big")), "heavy")
        last = width < 27 or heavy.isEmpty()
        own = rows if last else rows.join(heavy, rows.grp == heavy.big, "left_anti")
        done = own.select("grp", "fp") if done is None else done.unionByName(own.select("grp", "fp"))
        if last:
            return done
        rows = _dealt(saved(rows.join(heavy, rows.grp == heavy.big, "left_semi"), "large"), width)
        width = width // 4 * 3


def fingerprint_components(prints: DataFrame, most: int = MOST_BITS) -> DataFrame:
    """(node, comp) for the distinct fingerprints (column fp) that have a link of at most ``most`` <= 3 bits. Tasks take
    their groups one after the other, so what they hold does not follow the number of partitions."""
    if not 0 <= most <= MOST_BITS:
        raise ValueError("blocks of 16 bits serve for up to three differing bits")
    parts = max(int(prints.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    stars = _grouped(prints).repartition(parts, "grp").sortWithinPartitions("grp").mapInArrow(_stars(most, INDEXED_AT_ONCE), "u long, v long")
    return connected_components(stars)


def near_duplicates(docs: DataFrame, size: int = SHINGLE, most: int = MOST_BITS) -> DataFrame:
    """docs(doc_id, text) -> doc_id, fingerprint (16 lower-case hex digits), component_id (smallest doc_id reachable).

    Documents without words have fingerprint zero and are linked like any others. Repeated rows come out as often as
    they came in; a null doc_id stays null and never names a component that has an id; an empty table gives no rows.
    """
    rows = saved(document_fingerprints(docs, size), "fingerprints")
    least = saved(rows.groupBy("fp").agg(F.min("doc_id").alias("least")), "prints")
    comps = fingerprint_components(least.select("fp"), most)
    named = saved(least.join(comps, least.fp == comps.node, "left").select("fp", "least", F.coalesce("comp", "fp").alias("comp")), "named")
    ids = named.groupBy("comp").agg(F.min("least").alias("component_id"))
    of = named.join(ids, "comp").select(F.col("fp").alias("k"), "component_id")
    return rows.join(of, rows.fp == of.k).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, size: int = SHINGLE, most: int = MOST_BITS) -> DataFrame:
    """One row of docs for each component, with all its columns: that of the smallest doc_id, of several with it any
    one; null ids come last. Rows are told apart by a key of their own, so texts that differ stay whatever their ids."""
    rows, key = keyed(docs, "keyed")
    prints = saved(document_fingerprints(rows, size, key), "fingerprints")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", key)).alias("first")
    least = saved(prints.groupBy("fp").agg(first), "prints")
    comps = fingerprint_components(least.select("fp"), most)
    named = least.join(comps, least.fp == comps.node, "left").select(F.coalesce("comp", "fp").alias("comp"), "first")
    kept = named.groupBy("comp").agg(F.min("first").alias("first")).select(F.col(f"first.{key}").alias(key))
    return rows.join(kept, key, "left_semi").select(*docs.columns)
