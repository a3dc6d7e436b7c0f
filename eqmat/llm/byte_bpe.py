"""Byte-level BPE whose merge order is kept by a rank queue under a hierarchical bitmap.

Every pair of neighbours in a pre-token that can merge waits in the bucket of its rank. Which ranks wait is marked in
a bitmap of three levels, so the next rank is three find-first-set steps away, whatever the number of pairs. Merged
neighbours stay in their buckets and are skipped when they come up: an entry counts only if the pair that stands at
its position still has that rank. A pre-token of n bytes takes O(n log n) time at most, where scanning for the best
pair takes O(n^2); that is what very long pre-tokens need.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eqmat.llm.pretokens import Generations, byte_slices, safe_chunks

WORD = 64
MERGED_AT_ONCE = 1 << 20  # bytes


class RankQueue:
    """Buckets by rank under a bitmap of three levels of 64 bits a word (ranks below 64**3)."""

    __slots__ = ("top", "mid", "low", "buckets")

    def __init__(self):
        self.top, self.mid, self.low, self.buckets = 0, {}, {}, {}

    def push(self, rank: int, position: int) -> None:
        bucket = self.buckets.get(rank)
        if bucket is not None:
            bucket.append(position)
            return
        self.buckets[rank] = array("i", (position,))
        a, b = rank >> 12, rank >> 6
        self.top |= 1 << a
        self.mid[a] = self.mid.get(a, 0) | 1 << (b & 63)
        self.low[b] = self.low.get(b, 0) | 1 << (rank & 63)

    def first(self) -> int:
        """The lowest rank that waits, or -1."""
        if not self.top:
            return -1
        a = (self.top & -self.top).bit_length() - 1
        m = self.mid[a]
        b = a << 6 | ((m & -m).bit_length() - 1)
        w = self.low[b]
        return b << 6 | ((w & -w).bit_length() - 1)

    def pop(self, rank: int) -> list[int]:
        """Take the bucket of ``rank`` and clear its bits upward."""
        a, b = rank >> 12, rank >> 6
        self.low[b] &= ~(1 << (rank & 63))
        if not self.low[b]:
            self.mid[a] &= ~(1 << (b & 63))
            if not self.mid[a]:
                self.top &= ~(1 << a)
        return self.buckets.pop(rank)


class ByteBPE:
    """Encoder and decoder for one table of ranks (token bytes -> id, where the id is the merge rank)."""

    def __init__(self, ranks: dict[bytes, int], pattern: str, cache: int = 250_000):
        if max(ranks.values()) >= WORD**3:
            raise ValueError("too many ranks for three bitmap levels")
        self.ranks, self.pattern = ranks, regex.compile(pattern)
        self.bytes_of = [b""] * (max(ranks.values()) + 1)
        for token, i in ranks.items():
            self.bytes_of[i] = token
        self.chunks, self.words = Generations(cache), Generations(cache)

    @classmethod
    def from_file(cls, path: str, pattern: str, cache: int = 250_000) -> ByteBPE:
        with open(path, "rb") as f:
            return cls({base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}, pattern, cache)

    def merge(self, pieces: list[bytes], most: int = MERGED_AT_ONCE) -> list[bytes]:
        """Ids of each pre-token as little-endian 32-bit integers, about ``most`` bytes at a time; a longer pre-token is
        merged by itself."""
        out, own, held = [], [], 0
        for p in pieces:
            if own and held + len(p) > most:
                out += self._merge(own)
                own, held = [], 0
            own.append(p)
            held += len(p)
        return out + self._merge(own) if own else out

    def _merge(self, pieces: list[bytes]) -> list[bytes]:
        """All pre-tokens of the call share one queue: the merges of one never touch another, and a bucket that holds
        the positions of many is taken once."""
        ranks, get = self.ranks, self.ranks.get
        data = b"".join(pieces)
        total = len(data)
        # Four bytes a place: a very long pre-token costs some twenty times its bytes, not hundreds.
        end = array("i", range(1, total + 1))  # where the symbol that starts here ends, and so where the next one starts
        prev = array("i", range(-1, total))
        at = array("i", [-1]) * (total + 1)  # rank of the pair that starts here; -1: none, or no symbol starts here
        last = bytearray(total + 1)  # 1 where a pre-token ends
        starts, i = [], 0
        for p in pieces:
            starts.append(i)
            i += len(p)
            last[i] = 1
        for i in starts:
            prev[i] = -1
        queue = RankQueue()
        buckets, push = queue.buckets, queue.push
        for i in range(total - 1):
            if not last[i + 1] and (r := get(data[i : i + 2], -1)) >= 0:
                at[i] = r
                if r in buckets:
                    buckets[r].append(i)
                else:
                    push(r, i)
        while (rank := queue.first()) >= 0:
            bucket = queue.pop(rank)
            bucket = sorted(bucket)  # left to right; a new pair is longer than what was merged, so none of this rank can arise
            for i in bucket:
                if at[i] != rank:
                    continue  # stale
                j = end[i]
                e = end[i] = end[j]
                at[j] = -1
                if last[e]:
                    at[i] = -1
                else:
                    prev[e] = i
                    r = at[i] = get(data[i : end[e]], -1)
                    if r >= 0:
                        if r in buckets:
                            buckets[r].append(i)
                        else:
                            push(r, i)
                p = prev[i]
                if p >= 0:
                    r = at[p] = get(data[p:e], -1)
                    if r >= 0:
                        if r in buckets:
                            buckets[r].append(p)
                        else:
                            push(r, p)
        ids, cuts, i = array("I"), [0], 0
        while i < total:
            e = end[i]
            ids.append(ranks[data[i:e]])
            if last[e]:
                cuts.append(4 * len(ids))
            i = e
        flat = np.asarray(ids, "<u4").tobytes()
        return [flat[a:b] for a, b in zip(cuts, cuts[1:])]

    def _make_words(self, words: list[str]) -> list[bytes]:
        ranks, coded = self.ranks, [w.encode() for w in words]
        long = [w for w in coded if w not in ranks]
        merged = iter(self.merge(long))
        return [ranks[w].to_bytes(4, "little") if w in ranks else next(merged) for w in coded]

    def _make_chunks(self, chunks: list[str]) -> list[bytes]:
        cut = [[c] if c[1:].isalpha() and c[0] == " " else self.pattern.findall(c) for c in chunks]
        return self.words.joined(cut, self._make_words)

    def encode_batch(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers; a null text is empty."""
        self.chunks.turn()
        self.words.turn()
        return self.chunks.joined([safe_chunks(t) if t else [] for t in texts], self._make_chunks)

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, "<u4").tolist()))


_CODERS: dict[tuple, ByteBPE] = {}


def coder(path: str, pattern: str) -> ByteBPE:
    """The coder of a rank file, made once in each Python worker."""
    if (path, pattern) not in _CODERS:
        _CODERS[path, pattern] = ByteBPE.from_file(path, pattern)
    return _CODERS[path, pattern]


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list, list]]:
    for b in batches:
        for part in byte_slices(b):
            yield part.column(0).to_pylist(), part.column(1).to_pylist()


def _narrow(docs: DataFrame, column: str) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(column).cast("string" if column == "text" else "binary").alias("x"))


def encode(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """docs(doc_id, text) -> doc_id, n_tokens, ids (binary, little-endian unsigned 32-bit).

    A null or empty text has no ids; a null doc_id stays null; repeated rows are encoded each; an empty table gives no
    rows; other columns are not looked at.
    """

    def run(batches):
        own = coder(path, pattern)
        for doc, texts in _slices(batches):
            ids = own.encode_batch(texts)
            yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(ids, pa.binary())], names=["doc_id", "n_tokens", "ids"])

    return _narrow(docs, "text").mapInArrow(run, "doc_id long, n_tokens long, ids binary")


def decode(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """encoded(doc_id, ids) -> doc_id, text_bytes; null ids decode to no bytes."""

    def run(batches):
        own = coder(path, pattern)
        for doc, ids in _slices(batches):
            yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array([own.decode(x or b"") for x in ids], pa.binary())], names=["doc_id", "text_bytes"])

    return _narrow(encoded, "ids").mapInArrow(run, "doc_id long, text_bytes binary")


def round_trip(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """Encode and decode in one pass, for digests: docs(doc_id, text) -> doc_id, n_tokens, ids_sha256, decoded_sha256.

    A null or empty text has no ids and decodes to no bytes; a null doc_id stays null; repeated rows come out each; an
    empty table gives no rows; other columns are not looked at.
    """

    def run(batches):
        own = coder(path, pattern)
        for doc, texts in _slices(batches):
            ids = own.encode_batch(texts)
            cols = ([len(x) // 4 for x in ids], [hashlib.sha256(x).hexdigest() for x in ids], [hashlib.sha256(own.decode(x)).hexdigest() for x in ids])
            yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(cols[0], pa.int64()), pa.array(cols[1]), pa.array(cols[2])], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return _narrow(docs, "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
