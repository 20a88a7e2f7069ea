"""Near-duplicate vectors by epsilon grid order.

Vectors are scaled to length 1, so cosine >= t means a distance of at most
eps = sqrt(2 - 2t). On the leading principal directions a grid of width eps
gives each vector its cell; sorted by cell the vectors form a sequence, cut
into intervals of about ``capacity``. Pairs of intervals are refined from the
whole sequence downwards, four parts at a time, and a pair is skipped as soon as
the boxes of its intervals are further apart than eps. Pairs of intervals that
remain are joined in one task each, which goes on recursively in memory and
multiplies the last blocks as matrices, in double precision.

Exactly equal vectors are one row with a count. A task returns, for each
vector, how many it links with, and only such links as join two components in
it, so its output is linear in its input however dense a group is.

A vector that is null, empty, zero or has a null or non-finite component links
with nothing; vectors of different lengths do not link. The nodes are rows: an
id that repeats, or is null, gets a row for each. The principal
directions are fitted on ``fit_rows`` vectors (those of least hash); they
decide the order only, never the result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import components, discard, forest, materialize, workspace

AXES = 6
FAN = 4
SLACK = 1e-9


def _boxes(y: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return np.minimum.reduceat(y, starts), np.maximum.reduceat(y, starts)


def _apart(lo_a, hi_a, lo_b, hi_b) -> np.ndarray:
    """Squared distance of boxes."""
    return (np.maximum(0, np.maximum(lo_a - hi_b, lo_b - hi_a)) ** 2).sum(-1)


def near_blocks(y_a: np.ndarray, y_b: np.ndarray, same: bool, eps2: float, leaf: int) -> Iterator[tuple[int, int, int, int]]:
    """Recursive join of two sequences: the pairs of leaf intervals whose boxes
    are not provably distant. Of one sequence with itself, each pair once."""
    stack = [(0, len(y_a), 0, len(y_b))]
    while stack:
        a0, a1, b0, b1 = stack.pop()
        if a0 >= a1 or b0 >= b1 or same and b1 <= a0:
            continue
        if _apart(y_a[a0:a1].min(0), y_a[a0:a1].max(0), y_b[b0:b1].min(0), y_b[b0:b1].max(0)) > eps2:
            continue
        if a1 - a0 <= leaf and b1 - b0 <= leaf:
            yield a0, a1, b0, b1
            continue
        cut = lambda p, q: [(p, q)] if q - p <= leaf else [(p, m := p + -(-(q - p) // (2 * leaf)) * leaf), (m, q)]
        stack.extend((*u, *v) for u in cut(a0, a1) for v in cut(b0, b1))


def join_blocks(x_a: np.ndarray, x_b: np.ndarray, n_a: np.ndarray, n_b: np.ndarray, y_a: np.ndarray, y_b: np.ndarray, same: bool, least: float, eps2: float, leaf: int = 512):
    """(links of a, links of b, ends of joining links): ``n`` are copies."""
    links_a, links_b = np.zeros(len(x_a), np.int64), np.zeros(len(x_b), np.int64)
    ends: list[np.ndarray] = []
    for a0, a1, b0, b1 in near_blocks(y_a, y_b, same, eps2, leaf):
        hit = x_a[a0:a1] @ x_b[b0:b1].T >= least
        if same and a0 == b0:
            np.fill_diagonal(hit, False)
        if not hit.any():
            continue
        links_a[a0:a1] += hit @ n_b[b0:b1]
        if not (same and a0 == b0):
            links_b[b0:b1] += n_a[a0:a1] @ hit
        i, j = np.nonzero(hit)
        keep = forest(i, j + (0 if same and a0 == b0 else a1 - a0)) if len(i) > 1 else np.ones(len(i), bool)
        ends.append(np.stack([i[keep] + a0, j[keep] + b0]))
    return links_a, links_b, np.concatenate(ends, 1) if ends else np.zeros((2, 0), np.int64)


def _dense(column: pa.ChunkedArray, size: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.float64).reshape(-1, size)


def _links(rows: DataFrame, size: int, threshold: float, capacity: int, fit_rows: int, folder: str) -> DataFrame:
    """(rep, peer, links) of the distinct vectors (rep, n, v) of one length."""
    eps2, eps = 2 - 2 * threshold + SLACK, float(np.sqrt(max(2 - 2 * threshold, 1e-12)))
    sample = np.array([r[0] for r in rows.orderBy(F.xxhash64("v", F.lit(3)), "rep").limit(fit_rows).select("v").collect()], float).reshape(-1, size)
    sample /= np.linalg.norm(sample, axis=1, keepdims=True)
    axes = min(AXES, size)
    basis = np.linalg.eigh(np.cov(sample.T) if len(sample) > 1 else np.eye(size))[1].reshape(size, -1)[:, ::-1][:, :axes].copy()

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch.column(2).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, size)
            x = x / np.abs(x).max(1, keepdims=True)
            x = x / np.sqrt((x * x).sum(1, keepdims=True))
            y = x @ basis
            cell = np.floor(y / eps) + 32
            spot = np.zeros(len(x))
            for k in range(axes):
                spot = spot * 64 + np.clip(cell[:, k], 0, 63)
            spot = spot * 1024 + np.clip((y[:, 0] / eps - np.floor(y[:, 0] / eps)) * 1024, 0, 1023).astype(int)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(spot), pa.array([r.tobytes() for r in x], pa.binary()), pa.array(list(y), pa.list_(pa.float64()))], ["rep", "n", "spot", "x", "y"])

    placed = materialize(rows.mapInArrow(place, "rep long, n long, spot double, x binary, y array<double>"), folder, f"placed{size}")
    total = placed.count()
    parts = -(-total // capacity)
    cuts = sorted(set(placed.approxQuantile("spot", [k / parts for k in range(1, parts)], 0.1 / parts))) if parts > 1 else []
    if cuts:
        table = F.array(*[F.lit(c) for c in cuts]) if len(cuts) < 2000 else None
        interval = F.size(F.filter(table, lambda c: c < F.col("spot"))) if table is not None else None
        placed = placed.withColumn("interval", interval.cast("int")) if interval is not None else _interval(placed, cuts)
        placed = materialize(placed, folder, f"cut{size}")
    else:
        placed = placed.withColumn("interval", F.lit(0))
    box = lambda df, by: df.groupBy(by.alias("i")).agg(*[F.min(F.col(f"l{k}")).alias(f"l{k}") for k in range(axes)], *[F.max(F.col(f"h{k}")).alias(f"h{k}") for k in range(axes)])
    leaf_boxes = materialize(box(placed.select("interval", *[F.col("y")[k].alias(f"l{k}") for k in range(axes)], *[F.col("y")[k].alias(f"h{k}") for k in range(axes)]), F.col("interval")), folder, f"boxes{size}")
    level = 0
    while FAN**level < len(cuts) + 1:
        level += 1
    pairs = placed.sparkSession.createDataFrame([(0, 0)], "a int, b int")
    for up in range(level - 1, -1, -1):
        boxes = box(leaf_boxes.withColumnRenamed("i", "leaf"), F.floor(F.col("leaf") / FAN**up).cast("int")) if up else leaf_boxes
        kids = lambda c: F.explode(F.transform(F.sequence(F.lit(0), F.lit(FAN - 1)), lambda k: (F.col(c) * FAN + k).cast("int")))
        pairs = pairs.withColumn("a", kids("a")).withColumn("b", kids("b")).where("a <= b")
        for side in ("a", "b"):
            pairs = pairs.join(boxes.select(F.col("i").alias(side), *[F.col(f"{e}{k}").alias(f"{e}{k}{side}") for e in "lh" for k in range(axes)]), side)
        gap = sum((F.pow(F.greatest(F.lit(0.0), F.col(f"l{k}a") - F.col(f"h{k}b"), F.col(f"l{k}b") - F.col(f"h{k}a")), 2) for k in range(axes)), F.lit(0.0))
        pairs = materialize(pairs.where(gap <= eps2).select("a", "b"), folder, f"pairs{size}_{up}")
    left = placed.join(pairs.withColumn("interval", F.col("a")), "interval").select("a", "b", F.lit(0).alias("side"), "rep", "n", "x", "y")
    right = placed.join(pairs.where("a < b").withColumn("interval", F.col("b")), "interval").select("a", "b", F.lit(1).alias("side"), "rep", "n", "x", "y")

    def tile(table: pa.Table) -> pa.Table:
        side, rep, n = (table[c].to_numpy() for c in ("side", "rep", "n"))
        x, y = _dense(table["x"], size), np.array(table["y"].to_pylist(), float)
        cell = np.floor(y / eps)
        order = np.lexsort((*cell.T[::-1], side)) if len(cell) else np.zeros(0, int)
        rep, n, x, y, split = rep[order], n[order], x[order], y[order], int((side == 0).sum())
        same = split == len(rep)
        a, b = slice(0, split), slice(0, split) if same else slice(split, None)
        links_a, links_b, ends = join_blocks(x[a], x[b], n[a], n[b], y[a], y[b], same, threshold, eps2)
        links = links_a + links_b if same else np.concatenate([links_a, links_b])
        some = np.flatnonzero(links)
        nulls = pa.nulls(len(some), pa.int64())
        return pa.table({"rep": np.concatenate([rep[some], rep[a][ends[0]]]), "peer": pa.concat_arrays([nulls, pa.array(rep[b][ends[1]])]), "links": np.concatenate([links[some], np.zeros(ends.shape[1], np.int64)])})

    return left.unionAll(right).groupBy("a", "b").applyInArrow(tile, "rep long, peer long, links long")


def _interval(placed: DataFrame, cuts: list[float]) -> DataFrame:
    """Intervals by binary search in a broadcast list of cuts."""
    bounds = placed.sparkSession.sparkContext.broadcast(np.array(cuts))

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.append_column("interval", pa.array(np.searchsorted(bounds.value, batch.column(2).to_numpy(), "left").astype(np.int32)))

    return placed.mapInArrow(find, "rep long, n long, spot double, x binary, y array<double>, interval int")


def near_vectors(df: DataFrame, threshold: float = 0.95, key: str = "vec_id", vector: str = "embedding", capacity: int = 4096, fit_rows: int = 2000) -> DataFrame:
    """(key, n_links, component_id, kept) of every row."""
    spark, folder = df.sparkSession, workspace(df.sparkSession)
    v = F.col(vector).cast("array<double>")
    finite = F.forall(v, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf")))
    good = F.coalesce((F.size(v) > 0) & finite & F.exists(v, lambda c: c != 0), F.lit(False))
    named = df.select(F.col(key).cast("long").alias("id"), F.when(good, F.transform(v, lambda c: c + F.lit(0.0))).alias("v"))
    named = named.withColumn("h1", F.xxhash64("v")).withColumn("h2", F.xxhash64("v", F.lit(1)))
    # a class is one vector, whatever the ids of its rows; numbered once written
    classes = named.where("v is not null").groupBy("h1", "h2").agg(F.count("*").alias("n"), F.any_value("v").alias("v"))
    classes = materialize(materialize(classes, folder, "classes").withColumn("rep", F.monotonically_increasing_id()), folder, "distinct")
    discard(spark, folder, "classes")
    ids = named.where("v is not null").select("id", "h1", "h2").join(classes.select("h1", "h2", "rep", "n").hint("merge"), ["h1", "h2"])
    ids = materialize(ids.select("id", "rep", "n"), folder, "ids")
    one = classes.select("rep", "n", "v")
    sizes = sorted(r[0] for r in one.groupBy(F.size("v")).count().collect())
    found = spark.createDataFrame([], "rep long, peer long, links long")
    for size in sizes:
        found = found.unionAll(_links(one.where(F.size("v") == size), size, threshold, capacity, fit_rows, folder))
    found = materialize(found, folder, "found")
    comp = materialize(components(found.where("peer is not null").select(F.col("rep").alias("a"), F.col("peer").alias("b")), folder), folder, "comp")
    links = materialize(found.groupBy("rep").agg(F.sum("links").alias("links")).where("links > 0"), folder, "links")
    rows = ids.join(links.hint("merge"), "rep", "left").join(comp.withColumnRenamed("node", "rep").hint("merge"), "rep", "left")
    rows = rows.select("id", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).cast("long").alias("n_links"), F.coalesce("component", "rep").alias("component"))
    rows = materialize(rows, folder, "rows")
    least = materialize(rows.groupBy("component").agg(F.min("id").alias("component_id")), folder, "least")
    rows = rows.join(least.hint("merge"), "component").select("id", "n_links", "component_id")
    rest = named.where("v is null").select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    return rows.unionAll(rest).select(F.col("id").alias(key), "n_links", "component_id", F.col("id").eqNullSafe(F.col("component_id")).alias("kept"))
