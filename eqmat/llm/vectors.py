"""Embedding near-duplicates by tiled comparison in the order of principal components.

Equal vectors of a label are folded into one with a weight. The rest are cut into blocks along the first principal
coordinate; pairs of blocks whose intervals lie further apart than two unit vectors of the least cosine can be are not
shipped, and each pair that is shipped is compared by tiles of its sorted vectors, of which again only those near enough
meet. In a tile pair the products of the leading coordinates come first; what the other coordinates can still add
is bounded by the product of their norms, and a vector pair is left as soon as the bound falls short. Pairs that stay
are decided by the cosine of the vectors as given, in double precision. The rotation only orders the work, so it may
be fitted on a bounded sample.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eqmat.components import connected_components
from eqmat.storage import saved

LEAST, TILE, BLOCK_BYTES, SAMPLE = 0.93, 1024, 32 << 20, 20_000
TILES_A_BLOCK = 8
CUTS = (8, 16, 32)
SLACK = 1e-9


def principal_axes(sample: np.ndarray) -> np.ndarray:
    """Orthonormal columns by falling variance of the unit vectors."""
    unit = sample / np.linalg.norm(sample, axis=1, keepdims=True)
    values, axes = np.linalg.eigh(unit.T @ unit)
    return axes[:, np.argsort(values)[::-1]]


def linked_pairs(a: np.ndarray, b: np.ndarray, axes: np.ndarray, least: float, same: bool) -> tuple[np.ndarray, np.ndarray]:
    """Indices (i, j) of the pairs of rows of a and b with cosine >= least; i < j where a and b are the same tile."""
    na, nb = np.linalg.norm(a, axis=1), np.linalg.norm(b, axis=1)
    x, y = a / na[:, None] @ axes, b / nb[:, None] @ axes
    d = x.shape[1]
    cuts = [c for c in CUTS if c < d] + [d]
    rest = lambda m: np.sqrt(np.maximum(np.cumsum((m * m)[:, ::-1], axis=1)[:, ::-1], 0))
    sx, sy = rest(x), rest(y)
    c = cuts[0]
    dot = x[:, :c] @ y[:, :c].T
    alive = dot + (sx[:, c][:, None] * sy[:, c][None, :] if c < d else 0) >= least - SLACK
    if same:
        alive &= np.arange(len(a))[:, None] < np.arange(len(b))[None, :]
    i, j = np.nonzero(alive)
    dot = dot[i, j]
    for at, c in zip(cuts, cuts[1:], strict=False):
        dot = dot + np.einsum("ij,ij->i", x[i, at:c], y[j, at:c])
        stay = dot + (sx[i, c] * sy[j, c] if c < d else 0) >= least - SLACK
        i, j, dot = i[stay], j[stay], dot[stay]
    exact = np.einsum("ij,ij->i", a[i], b[j]) / (na[i] * nb[j]) >= least
    return i[exact], j[exact]


def least_labels(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """For each of n items the smallest item that the links a-b connect it with."""
    comp = np.arange(n)
    while True:
        x, y = comp[a], comp[b]
        if (x == y).all():
            return comp
        np.minimum.at(comp, np.maximum(x, y), np.minimum(x, y))
        while (comp[comp] != comp).any():
            comp = comp[comp]


def _side(row: pa.RecordBatch, side: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Nodes, copies, first coordinates and vectors of one block, straight from the Arrow buffers, sorted by coordinate."""
    flat = lambda c: row.column(f"{side}_{c}").flatten()
    node, copies, first, vec = flat("node").to_numpy(zero_copy_only=False), flat("copies").to_numpy(zero_copy_only=False), flat("first").to_numpy(zero_copy_only=False), flat("vec")
    vec = vec.flatten().to_numpy(zero_copy_only=False).reshape(len(node), -1)
    order = np.lexsort((node, first))
    return node[order], copies[order], first[order], vec[order]


def _tiled_pairs(x: tuple, y: tuple, axes: np.ndarray, least: float, same: bool, tile: int) -> tuple[np.ndarray, np.ndarray]:
    """Linked pairs of two sorted blocks, tile by tile."""
    far, out = math.sqrt(2 - 2 * least) + SLACK, []
    for i in range(0, len(x[0]), tile):
        for j in range(i if same else 0, len(y[0]), tile):
            a, b = slice(i, i + tile), slice(j, j + tile)
            if x[2][a][0] - y[2][b][-1] <= far and y[2][b][0] - x[2][a][-1] <= far:
                p, q = linked_pairs(x[3][a], y[3][b], axes, least, same and i == j)
                out.append((p + i, q + j))
    return tuple(np.concatenate(c) for c in zip(*out, strict=True)) if out else (np.zeros(0, np.int64),) * 2


def _compare(axes: dict[int, np.ndarray], least: float, tile: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                row = batch.slice(k, 1)
                same = row.column("a_tile")[0].as_py() == row.column("b_tile")[0].as_py()
                x = _side(row, "a")
                y = x if same else _side(row, "b")
                d = x[3].shape[1]
                i, j = _tiled_pairs(x, y, axes.get(d, np.eye(d)), least, same, tile)
                if not len(i):
                    continue
                if same:
                    node, weight, n, a, b = x[0], x[1], len(x[0]), i, j
                else:
                    node, weight, n = np.concatenate([x[0], y[0]]), np.concatenate([x[1], y[1]]), len(x[0]) + len(y[0])
                    a, b = i, j + len(x[0])
                links = np.bincount(a, weight[b], n) + np.bincount(b, weight[a], n)
                rank = np.argsort(np.argsort(node, kind="stable"), kind="stable")
                top = np.sort(node)[least_labels(n, rank[a], rank[b])][rank]
                hit = np.flatnonzero(links)
                yield pa.RecordBatch.from_arrays([pa.array(node[hit]), pa.array(links[hit].astype(np.int64)), pa.array(top[hit])], names=["node", "links", "top"])

    return run


def _coordinate(axes: dict[int, np.ndarray], marks: dict[int, np.ndarray]):
    """Add the first principal coordinate and its share of the sample below it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            first, share = [], []
            for v in b.column("vec").to_pylist():
                x = np.array(v, np.float64)
                axis, mark = axes.get(len(x)), marks.get(len(x))
                p = float(x @ (axis[:, 0] if axis is not None else np.eye(len(x))[:, 0]) / np.linalg.norm(x))
                first.append(p)
                share.append(float(np.searchsorted(mark, p) / (len(mark) + 1)) if mark is not None else 0.0)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(first), pa.array(share)], names=[*b.schema.names, "first", "share"])

    return run


def near_duplicates(embeddings: DataFrame, least: float = LEAST, tile: int = TILE, sample: int = SAMPLE) -> DataFrame:
    """embeddings(vec_id, embedding, label) -> vec_id, n_links, component_id, kept.

    Vectors link when their labels are equal and their cosine is at least ``least`` (between 0 and 1). A row whose id,
    label or vector is null, or whose vector is empty, zero, or holds a null or a number that is not finite, links with
    nothing and stays. Vectors of different lengths do not link. Repeated rows are vectors like others. The axes are
    fitted on about ``sample`` vectors picked by hash.
    """
    if not 0 < least <= 1:
        raise ValueError("least must lie above 0 and not above 1")
    sound = "vec_id is not null and label is not null and embedding is not null and size(embedding) > 0 and forall(embedding, x -> x is not null and not isnan(x) and abs(x) < double('infinity')) and exists(embedding, x -> x <> 0)"
    rows = embeddings.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label"), F.col("embedding").cast("array<double>").alias("embedding")).withColumn("sound", F.coalesce(F.expr(sound), F.lit(False)))
    rows = rows.withColumn("vkey", F.when(F.col("sound"), F.md5(F.concat_ws(",", F.col("embedding").cast("array<string>")).cast("binary"))))
    folded = rows.where("sound").groupBy("label", "vkey").agg(F.min("vec_id").alias("node"), F.count("*").alias("copies"), F.min("embedding").alias("vec"))
    folded = saved(folded, "vectors")
    n = folded.count()
    picked = folded.where(F.pmod(F.xxhash64("vkey"), F.lit(1_000_000)) < F.lit(int(1_000_000 * min(1.0, sample / max(n, 1))))).select("vec").collect()
    by_size: dict[int, list] = {}
    for r in picked:
        by_size.setdefault(len(r["vec"]), []).append(r["vec"])
    axes = {d: principal_axes(np.array(v)) for d, v in by_size.items()}
    marks = {d: np.quantile(np.array(v) / np.linalg.norm(np.array(v), axis=1, keepdims=True) @ axes[d][:, 0], np.linspace(0, 1, 1025)[1:-1]) for d, v in by_size.items()}
    kind = folded.schema["label"].dataType.simpleString()
    placed = saved(folded.select("node", "copies", "label", "vec").mapInArrow(_coordinate(axes, marks), f"node long, copies long, label {kind}, vec array<double>, first double, share double"), "placed")
    group = ["label", "d"]
    placed = placed.withColumn("d", F.size("vec"))
    counts = placed.groupBy(*group).agg(F.count("*").alias("n"))
    # A block is some tiles, fewer where vectors are long: what travels to each partner, and what a task holds twice.
    block = F.greatest(F.lit(1), F.least(F.lit(TILES_A_BLOCK * tile), F.floor(F.lit(BLOCK_BYTES) / (8 * F.col("d")))))
    cut = placed.join(counts, group).withColumn("slot", F.floor(F.col("share") * F.ceil(F.col("n") / block)))
    crowd = cut.groupBy(*group, "slot").agg(F.count("*").alias("m"))
    cut = cut.join(crowd, [*group, "slot"]).withColumn("tile", F.concat_ws(":", "slot", F.pmod(F.xxhash64("node"), F.ceil(F.col("m") / block))))
    tiles = saved(cut.groupBy(*group, "tile").agg(F.min("first").alias("lo"), F.max("first").alias("hi"), F.collect_list(F.struct("node", "copies", "first", "vec")).alias("rows")), "tiles")  # about `block` rows each
    far = math.sqrt(2 - 2 * least) + SLACK
    a, b = (tiles.select(*[F.col(c).alias(f"{s}_{c}") for c in ("label", "d", "tile", "lo", "hi")]) for s in "ab")
    pairs = a.join(b, (F.col("a_label") == F.col("b_label")) & (F.col("a_d") == F.col("b_d")) & (F.col("a_tile") <= F.col("b_tile")) & (F.col("a_lo") - F.col("b_hi") <= far) & (F.col("b_lo") - F.col("a_hi") <= far))
    pairs = pairs.select(F.col("a_label").alias("label"), F.col("a_d").alias("d"), "a_tile", "b_tile")
    full = lambda s: tiles.select("label", "d", F.col("tile").alias(f"{s}_tile"), *[F.col(f"rows.{c}").alias(f"{s}_{c}") for c in ("node", "copies", "first", "vec")])
    parts = int(embeddings.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    work = pairs.join(full("a"), [*group, "a_tile"]).join(full("b"), [*group, "b_tile"]).drop(*group)
    found = saved(work.repartition(parts).mapInArrow(_compare(axes, least, tile), "node long, links long, top long"), "links")
    links = found.groupBy("node").agg(F.sum("links").alias("links"))
    comps = connected_components(found.select(F.col("node").alias("u"), F.col("top").alias("v"))).withColumnRenamed("node", "c_node")
    of = folded.select("label", "vkey", "node", "copies").join(links, "node", "left").join(comps, F.col("node") == F.col("c_node"), "left")
    of = of.select(F.col("label").alias("l"), F.col("vkey").alias("k"), (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n"), F.coalesce("comp", "node").alias("c"))
    out = rows.select("vec_id", "label", "vkey").join(of, (F.col("label") == F.col("l")) & (F.col("vkey") == F.col("k")), "left")
    return out.select("vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), F.coalesce("c", "vec_id").alias("component_id")).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
