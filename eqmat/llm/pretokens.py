"""Small tools that operators on whole texts share: bounded word caches, safe splitting at spaces, and slices of Arrow
batches that are bounded by bytes."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_AT_SAFE_SPACE = re.compile(r"(?<=\S) (?=\S)")
_UNSAFE = re.compile(r" \s|\s |\A\s|\s\Z")


class Generations:
    """A dict in two generations. When the young one is full it becomes the old one, so memory is bounded and
    frequent words, which are asked for again, stay."""

    def __init__(self, most: int):
        self.most, self.young, self.old = most, {}, {}

    def turn(self) -> None:
        """Called between batches, so that what a batch has looked up stays at hand while it is used."""
        if len(self.young) > self.most:
            self.old, self.young = self.young, {}

    def clear(self) -> None:
        self.young, self.old = {}, {}

    def values(self, keys: list, make) -> list:
        """The value of each key; make(list of distinct missing keys) gives those that neither generation holds."""
        young, old = self.young, self.old
        out = list(map(young.get, keys))
        gaps = [i for i, v in enumerate(out) if v is None]
        if gaps:
            absent = list(dict.fromkeys([keys[i] for i in gaps]))
            found = list(map(old.get, absent))
            young.update((k, v) for k, v in zip(absent, found, strict=True) if v is not None)
            missing = [k for k, v in zip(absent, found, strict=True) if v is None]
            if missing:
                young.update(zip(missing, make(missing), strict=True))
            for i in gaps:
                out[i] = young[keys[i]]
        return out

    def joined(self, lists: list[list], make) -> list[bytes]:
        """For each list of keys, its values one after the other."""
        flat = [k for keys in lists for k in keys]
        values, out, at = self.values(flat, make), [], 0
        for keys in lists:
            out.append(b"".join(values[at : at + len(keys)]))
            at += len(keys)
        return out


def safe_chunks(text: str) -> list[str]:
    """Cut text before each single space that stands between two other non-space characters; that space begins the
    next piece. A pattern whose matches hold a space only in front never matches across such a cut."""
    if not text:
        return []
    parts = _AT_SAFE_SPACE.split(text) if _UNSAFE.search(text) else text.split(" ")
    return [parts[0], *[" " + p for p in parts[1:]]]


def byte_slices(batch: pa.RecordBatch, rows: int = 1024, size: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The rows of a batch in order, at most ``rows`` and, but for a single longer one, ``size`` bytes of its last column
    at a time: one worker never holds more than that as Python values, whatever the texts."""
    n = batch.num_rows
    if not n:
        return
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(batch.num_columns - 1)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    at = 0
    while at < n:
        done = ends[at - 1] if at else 0
        to = max(at + 1, min(at + rows, n, int(np.searchsorted(ends, done + size, side="right"))))
        yield batch.slice(at, to - at)
        at = to
