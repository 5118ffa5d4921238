"""Near-duplicate vectors by int8 tile products with per-vector error bounds."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_batches, discard, small, stored
from .components import components, local_roots

#: Covers the rounding of the bounds themselves in double precision.
SLOP = 1e-9
#: Columns whose int8 products add up exactly in float32: 1024 * 127 * 127 < 2^24.
EXACT_COLUMNS = 1024


def quantise(unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Int8 codes, scale, length of the decoded vector and length of what the codes miss, for each row."""
    scale = np.abs(unit).max(axis=1) / 127
    codes = np.rint(unit / scale[:, None]).astype(np.int8)
    decoded = codes * scale[:, None]
    return codes, scale, np.linalg.norm(decoded, axis=1), np.linalg.norm(unit - decoded, axis=1)


def code_products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Integer products of int8 codes, exact: float32 holds each partial sum of EXACT_COLUMNS columns."""
    out = None
    for k in range(0, a.shape[1], EXACT_COLUMNS):
        part = a[:, k : k + EXACT_COLUMNS].astype(np.float32) @ b[:, k : k + EXACT_COLUMNS].astype(np.float32).T
        out = part if out is None else out.astype(np.float64) + part
    return out


def tile_links(x: np.ndarray, y: np.ndarray | None, threshold: float, step: int = 512) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs (row of x, row of y) with cosine >= threshold; y None: pairs i < j of x.

    |u.v - s t (p.q)| <= |s p| e_v + e_u |t q| + e_u e_v for codes p, q, scales s, t and residual
    lengths e. A pair is passed over only if the product plus that bound stays below the threshold;
    all others are computed from the vectors in double precision.
    """
    own = y is None
    unit = lambda m: m / np.linalg.norm(m, axis=1, keepdims=True)
    ux = unit(x)
    uy = ux if own else unit(y)
    px, sx, nx, ex = quantise(ux)
    py, sy, ny, ey = (px, sx, nx, ex) if own else quantise(uy)
    far = float((ny + ey).max()) if len(ny) else 0.0
    left, right = [], []
    for a in range(0, len(ux), step):
        b0 = a if own else 0
        near = code_products(px[a : a + step], py[b0:]) * (sx[a : a + step, None] * sy[None, b0:])
        widest = nx[a : a + step].max() * ey.max() + ex[a : a + step].max() * far
        i, j = np.nonzero(near >= threshold - widest - SLOP)
        value = near[i, j]
        i, j = i + a, j + b0
        keep = value + nx[i] * ey[j] + ex[i] * (ny[j] + ey[j]) + SLOP >= threshold
        if own:
            keep &= i < j
        i, j = i[keep], j[keep]
        for k in range(0, len(i), 1 << 17):
            p, q = i[k : k + (1 << 17)], j[k : k + (1 << 17)]
            u, v = x[p], (x if own else y)[q]
            ok = np.einsum("ij,ij->i", u, v) / (np.linalg.norm(u, axis=1) * np.linalg.norm(v, axis=1)) >= threshold
            left.append(p[ok])
            right.append(q[ok])
    none = np.zeros(0, np.int64)
    return (np.concatenate(left), np.concatenate(right)) if left else (none, none)


def _tile_task(threshold: float):
    def run(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        n, dim = table.num_rows, table.column("dim")[0].as_py()
        vectors = table.column("embedding").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(n, dim)
        vectors = np.ldexp(vectors, -np.frexp(np.abs(vectors).max(axis=1))[1][:, None])  # exact; no square overflows
        tile, ids, copies = (table.column(k).to_numpy() for k in ("tile", "rep", "copies"))
        lo, hi = table.column("lo")[0].as_py(), table.column("hi")[0].as_py()
        order = np.argsort(ids, kind="stable")
        vectors, tile, ids, copies = vectors[order], tile[order], ids[order], copies[order]
        if lo == hi:
            i, j = tile_links(vectors, None, threshold)
        else:
            p, q = np.flatnonzero(tile == lo), np.flatnonzero(tile == hi)
            i, j = tile_links(vectors[p], vectors[q], threshold)
            i, j = p[i], q[j]
        links = np.zeros(n, np.int64)
        np.add.at(links, i, copies[j])
        np.add.at(links, j, copies[i])
        root = local_roots(n, i, j)
        some = np.flatnonzero(links)
        return pa.table({"id": ids[some], "links": links[some], "other": ids[root[some]]})

    return run


def embedding_links(rows: DataFrame, threshold: float = 0.93, tile_rows: int = 4096, key: str = "vec_id", vector: str = "embedding", group: str = "label") -> DataFrame:
    """One row per vector: key, n_links, component_id, kept.

    Vectors of one group and one length are compared, all with all, in tiles: equal vectors first
    become one with a count; the rest of a group is dealt by hash into tiles of about `tile_rows`,
    and one task takes one pair of tiles, whatever the group's size. A task returns for each vector
    with links their number and one link to its component there, never the pairs.

    Null group, null, empty or zero vector, null or non-finite component: no links, own component.
    Repeated rows count as vectors of their own. Other columns are ignored. An empty table gives an
    empty result.
    """
    spark = rows.sparkSession
    bounded_batches(spark)
    rows = rows.select(F.col(key).alias("id"), F.col(vector).alias("embedding"), F.col(group).alias("label"))
    finite = F.forall("embedding", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    usable = F.coalesce(F.col("label").isNotNull() & finite & F.exists("embedding", lambda v: v != 0), F.lit(False))
    valid = rows.where(usable)
    reps = stored(valid.groupBy("label", "embedding").agg(F.min("id").alias("rep"), F.count("*").alias("copies")).withColumn("dim", F.size("embedding")), "vectors")
    sizes = stored(reps.groupBy("label", "dim").agg(F.ceil(F.count("*") / tile_rows).cast("int").alias("tiles")), "sizes")
    dealt = reps.join(small(sizes, 10_000), ["label", "dim"]).withColumn("tile", F.pmod(F.xxhash64("rep", F.lit(7)), "tiles").cast("int"))
    dealt = dealt.withColumn("with", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    dealt = dealt.select("label", "dim", F.least("tile", "with").alias("lo"), F.greatest("tile", "with").alias("hi"), "tile", "rep", "copies", "embedding")
    found = stored(dealt.groupBy("label", "dim", "lo", "hi").applyInArrow(_tile_task(threshold), "id long, links long, other long"), "tiles")
    discard(spark, sizes)
    comps = components(found.select(F.col("id").alias("a"), F.col("other").alias("b")))
    counts = found.groupBy("id").agg(F.sum("links").alias("links"))
    known = counts.join(comps, "id", "left").select(F.col("id").alias("rep"), "links", "component")
    classes = reps.join(known, "rep", "left").select("label", "embedding", "copies", "rep", F.coalesce("links", F.lit(0)).alias("links"), F.coalesce("component", "rep").alias("component"))
    classes = stored(classes, "classes")
    discard(spark, found, reps)
    linked = valid.join(classes, ["label", "embedding"]).select("id", (F.col("links") + F.col("copies") - 1).alias("n_links"), F.col("component").alias("component_id"))
    alone = rows.where(~usable).select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    return linked.union(alone).select(F.col("id").alias(key), "n_links", "component_id", (F.col("id") == F.col("component_id")).alias("kept"))


def duplicates_within_tiles(vectors: np.ndarray, threshold: float = 0.93) -> Iterator[tuple[int, int]]:
    """The links among the rows of one array, for use without Spark."""
    yield from zip(*(k.tolist() for k in tile_links(np.asarray(vectors, float), None, threshold)), strict=True)
