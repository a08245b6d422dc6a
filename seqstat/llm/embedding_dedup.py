"""Embedding near-duplicates: int8 tile products with rigorous error bounds, full precision only where needed.

Equal vectors are one class. Classes are dealt to the nearest of a bounded number of pivots and in a pivot's cell to blocks of
bounded size; a pair of blocks whose pivots lie further apart than the blocks' radii and the limit's angle allow is never
made. For a pair of blocks, unit vectors u are quantised to s*q with int8 q, and e = |u - s*q| is computed, not estimated: then
|u.v - s*s'*(q.q')| <= e + e' + e*e'. Pairs that this bound leaves possible are recomputed in double precision.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqstat.llm.graph import components
from seqstat.llm.shared import attach_class, sample_rows, stage

#: For rounding in the bounds themselves: far above the error of sums in double precision, far below any distance that matters.
SLACK = 1e-9


def usable(vector: Column) -> Column:
    fine = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.coalesce(fine & F.exists(vector, lambda x: x != 0), F.lit(False))


def unit(m: np.ndarray) -> np.ndarray:
    """Rows in double precision over their lengths, scaled first, so that neither end of the float range is lost."""
    m = m.astype(np.float64)
    m = m / np.abs(m).max(axis=1, keepdims=True)
    return m / np.sqrt((m * m).sum(axis=1, keepdims=True))


def quantise(u: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(int8 rows, scale of each, exact error of each) of unit rows."""
    scale = np.abs(u).max(axis=1) / 127
    q = np.rint(u / scale[:, None]).astype(np.int8)
    return q, scale, np.sqrt(((u - scale[:, None] * q) ** 2).sum(axis=1)) + SLACK


def tile_links(u: np.ndarray, v: np.ndarray, limit: float, same: bool, rows: int = 512) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs (i of u, j of v) with cosine >= limit, a strip of rows at a time; i < j if both are one block."""
    (p, s, e), (q, t, f) = quantise(u), quantise(v)
    kind = np.float32 if u.shape[1] * 127 * 127 < 1 << 24 else np.float64  # sums of int8 products stay exact
    right = q.astype(kind).T
    for a in range(0, len(u), rows):
        b = min(a + rows, len(u))
        product = (p[a:b].astype(kind) @ right).astype(np.float64) * s[a:b, None] * t
        bound = e[a:b, None] + f + e[a:b, None] * f + SLACK
        i, j = np.nonzero(product >= limit - bound)
        i += a
        if same:
            i, j = i[i < j], j[i < j]
        for k in range(0, len(i), 1 << 18):
            x, y = i[k : k + (1 << 18)], j[k : k + (1 << 18)]
            exact = np.einsum("nd,nd->n", u[x], v[y])
            near = exact >= limit
            if near.any():
                yield x[near], y[near]


def merge_least(parent: np.ndarray, i: np.ndarray, j: np.ndarray) -> None:
    """Union the pairs in ``parent``; every entry ends at the least index it is joined to."""
    while True:
        while (parent != parent[parent]).any():
            parent[:] = parent[parent]
        a, b = parent[i], parent[j]
        apart = a != b
        if not apart.any():
            return
        np.minimum.at(parent, np.maximum(a, b)[apart], np.minimum(a, b)[apart])


def blocks(classes: DataFrame, pivots: int, size: int, seed: int) -> tuple[DataFrame, dict[int, float], np.ndarray]:
    """(block, cell, radius, dim, reps, counts, vectors as bytes), radius of each cell, pivots.

    Pivots are drawn by a hash, so their number doesn't follow the input; a cell's classes are dealt to its blocks by hash.
    """
    drawn = sample_rows(classes, pivots, seed, "rep")
    centres = [unit(np.array([r["embedding"]]))[0] for r in drawn]
    sent = classes.sparkSession.sparkContext.broadcast(centres)

    def nearest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cells, angles = np.full(batch.num_rows, -1), np.zeros(batch.num_rows)
            vectors = batch.column(2)
            sizes = np.diff(vectors.offsets.to_numpy())
            for dim in np.unique(sizes):
                at = np.flatnonzero(sizes == dim)
                own = [k for k, c in enumerate(sent.value) if len(c) == dim]
                if own:
                    u = unit(np.stack([vectors[int(i)].values.to_numpy() for i in at]))
                    cosines = u @ np.stack([sent.value[k] for k in own]).T
                    best = cosines.argmax(axis=1)
                    cells[at] = np.array(own)[best]
                    angles[at] = np.arccos(np.clip(cosines[np.arange(len(at)), best], -1, 1)) + 1e-6
                else:
                    cells[at], angles[at] = -int(dim), np.pi  # no pivot of this size: a cell of its own, never pruned
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(cells), pa.array(angles)], ["rep", "n", "embedding", "cell", "angle"])

    dealt = stage(classes.select("rep", "n", "embedding").mapInArrow(nearest, "rep long, n long, embedding array<float>, cell long, angle double"), "cells")
    cells = dealt.groupBy("cell").agg(F.count(F.lit(1)).alias("members"), F.max("angle").alias("reach"))
    known = cells.withColumn("parts", F.ceil(F.col("members") / size))
    dealt = dealt.join(F.broadcast(known.select("cell", "parts")), "cell")  # at most one row per pivot and vector size
    block = F.concat_ws(":", "cell", F.pmod(F.xxhash64("rep"), "parts"))

    def packed(key: tuple, table: pa.Table) -> pa.Table:
        matrix = table["embedding"].combine_chunks().values.to_numpy().astype(np.float32).reshape(table.num_rows, -1)
        row = {"block": key[0].as_py(), "cell": table["cell"][0].as_py(), "radius": max(table["angle"].to_pylist()), "dim": matrix.shape[1]}
        row |= {"reps": table["rep"].to_numpy().tobytes(), "counts": table["n"].to_numpy().tobytes(), "vectors": matrix.tobytes()}
        return pa.Table.from_pylist([row], schema=pa.schema([("block", pa.string()), ("cell", pa.int64()), ("radius", pa.float64()), ("dim", pa.int64()), ("reps", pa.binary()), ("counts", pa.binary()), ("vectors", pa.binary())]))

    packed_rows = dealt.withColumn("block", block).groupBy("block").applyInArrow(packed, "block string, cell long, radius double, dim long, reps binary, counts binary, vectors binary")
    reach = {r["cell"]: r["reach"] for r in known.select("cell", "reach").collect()}
    return stage(packed_rows, "blocks"), reach, centres


def near_cells(reach: dict[int, float], centres: list[np.ndarray], limit: float) -> list[tuple[int, int]]:
    """Pairs of cells (one at most the other) that may hold a pair of vectors within the limit."""
    wide, out = np.arccos(min(1.0, max(-1.0, limit))), []
    for a in sorted(reach):
        for b in (b for b in sorted(reach) if b >= a):
            if a < 0 or b < 0:
                if a == b:
                    out.append((a, b))
            elif len(centres[a]) == len(centres[b]) and np.arccos(np.clip(centres[a] @ centres[b], -1, 1)) - reach[a] - reach[b] <= wide + 1e-6:
                out.append((a, b))
    return out


def near_vectors(vectors: DataFrame, limit: float = 0.95, pivots: int = 64, size: int = 2048, seed: int = 29) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of ``vectors`` (vec_id, embedding).

    Vectors that are null, empty, zero or hold null or non-finite components link with nothing, as do vectors of different
    lengths with each other; equal vectors and repeated rows link; a row without an id is its own component, without an
    id; an empty table gives no rows. Nothing is given per pair: a tile hands on link counts and, for each linked class, the
    least class it is joined to.
    """
    spark = vectors.sparkSession
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<float>").alias("embedding"))
    good = usable(F.col("embedding")) & F.col("vec_id").isNotNull()
    classes = stage(rows.where(good).groupBy("embedding").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("n")), "vector-classes")
    table, reach, centres = blocks(classes, pivots, size, seed)
    pairs = spark.createDataFrame(near_cells(reach, centres, limit), "ca long, cb long")  # at most pivots squared
    heads = table.select("block", "cell", "radius")
    left = heads.withColumnsRenamed({"block": "a", "cell": "ca", "radius": "ra"})
    right = heads.withColumnsRenamed({"block": "b", "cell": "cb", "radius": "rb"})
    tiles = left.join(F.broadcast(pairs), "ca").join(right, "cb").where("ca < cb or a <= b").select("a", "b")
    data = table.select("block", "dim", "reps", "counts", "vectors")
    for side in "ab":
        tiles = tiles.join(data.withColumnsRenamed({c: c + side for c in data.columns}).withColumnRenamed(f"block{side}", side), side)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                get = lambda name, r=row, b=batch: b.column(name)[r].as_buffer() if not name.startswith("dim") else b.column(name)[r].as_py()
                same = batch.column("a")[row].as_py() == batch.column("b")[row].as_py()
                reps, counts, units = [], [], []
                for side in "ab":
                    reps.append(np.frombuffer(get(f"reps{side}"), np.int64))
                    counts.append(np.frombuffer(get(f"counts{side}"), np.int64))
                    units.append(unit(np.frombuffer(get(f"vectors{side}"), np.float32).reshape(-1, get(f"dim{side}"))))
                shift = 0 if same else len(reps[0])
                ids = reps[0] if same else np.concatenate(reps)
                weight = counts[0] if same else np.concatenate(counts)
                order = np.argsort(ids)
                place = np.empty(len(ids), np.int64)
                place[order] = np.arange(len(ids))
                links, parent = np.zeros(len(ids), np.int64), np.arange(len(ids))
                for i, j in tile_links(units[0], units[1], limit, same):
                    x, y = i, j + shift
                    links += np.bincount(x, weight[y], len(ids)).astype(np.int64) + np.bincount(y, weight[x], len(ids)).astype(np.int64)
                    merge_least(parent, place[x], place[y])
                at = np.flatnonzero(links)
                yield pa.RecordBatch.from_arrays([pa.array(ids[at]), pa.array(links[at]), pa.array(ids[order[parent[place[at]]]])], ["rep", "links", "least"])

    found = stage(tiles.mapInArrow(run, "rep long, links long, least long"), "tile-links")
    joined = components(found.select(F.col("rep").alias("a"), F.col("least").alias("b")))
    totals = found.groupBy("rep").agg(F.sum("links").alias("links"))
    named = classes.join(totals, "rep", "left").join(joined.withColumnRenamed("node", "rep"), "rep", "left")
    named = named.select("embedding", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    linked = attach_class(rows.where(good), "embedding", named, "vec_id").select("vec_id", "n_links", "component_id")
    alone = rows.where(~good).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return linked.union(alone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
