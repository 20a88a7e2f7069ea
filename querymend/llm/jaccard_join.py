"""Exact Jaccard join of word n-gram sets by count vectors.

1. Sets. Each text gives the set of its distinct shingles' 64-bit hashes (mixed
   with the place of every byte, so that no text cancels out); sets with equal
   names are one class, so copies cost one row. A name is 128 bits; in the few
   classes whose first 64 bits agree and whose others do not, these decide. A
   class is joined once.
2. Meeting places. The hash range is cut into m groups. Two sets with J >= t
   differ in at most d = (1-t)/(1+t) * (|A|+|B|) shingles, so in at most d
   groups; with m > d some group is the same in both. A set is sent under the
   content of each of its groups (sizes are banded by powers of two; a set near
   the top of a band is sent to the next one too). This loses no pair and caps
   nothing. Common passages are no hot keys, as a group mixes them with a
   document's own shingles.
3. Stars. In each meeting place every class is paired with the least and the
   greatest one. The bound below, then the sets themselves, decide. Where a
   place still holds several components, this can be repeated ``more_stars``
   times with two other classes as centres, for the classes outside the
   centre's component.
4. R-tree. In places that still hold classes of different components, count
   vectors (shingles by ``GROUPS`` coarse groups) are packed into an R-tree; a
   node at any height is its upper corner and its range of sizes. The overlap
   of two nodes is at most the sum of the minima of their corners, which prunes
   whole subtrees from the roots down; pairs that survive and lie in different
   components are verified. A row names the last few open places of its class
   before this one, and a pair that met in one of them is left to it. Large
   places are cut into blocks and joined block by block.
5. Components of all verified links.

Rows with null or empty texts have empty sets and link with nothing. Ids are
longs; the nodes are rows, so an id with several texts gets a row for each. Other
columns are left behind.

For components it is enough to verify pairs that lie apart. ``jaccard_links``
leaves out steps 3 and the test for components and verifies every pair of
classes that the tree lets through: all links, and their number for each row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import BASE, U, components, discard, materialize, may_hold, mix, ragged, slices, word_shingles, workspace

#: Groups of the count vectors; a count is one byte, what is over 255 is kept
#: apart as the set's size less the sum of its vector.
GROUPS = 512
#: Points of a leaf and children of a node.
LEAF = 16
#: Earlier open places of a class that a row of a later one names.
EARLIER = 16


class Plan:
    """Threshold num/den on shingles of ``width`` words."""

    def __init__(self, width: int = 4, num: int = 85, den: int = 100):
        self.width, self.num, self.den = width, num, den

    def differ(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Most shingles that sets of these sizes may differ by."""
        return (self.den - self.num) * (a + b) // (self.den + self.num)

    def enough(self, overlap: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return self.den * overlap >= self.num * (a + b - overlap)

    def keys(self, values: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Meeting-place keys of each set, and the bounds of each set's keys."""
        n = np.diff(bounds)
        band = np.floor(np.log2(np.maximum(n, 1))).astype(np.int64)
        parts = []
        for up in (0, 1):
            level = band + up
            top = (1 << (level + 1)) - 1
            goes = (n > 0) if up == 0 else (n > 0) & (n * self.den // self.num > (1 << level) - 1)
            m = self.differ(top, top) + 2
            m += (m > 8) * (m // 32)
            pick = np.flatnonzero(goes)
            if not len(pick):
                continue
            row = np.repeat(pick, n[pick])
            at = np.concatenate([np.arange(bounds[i], bounds[i + 1]) for i in pick])
            v, mm = values[at], m[row].astype(U)
            with np.errstate(over="ignore"):
                group = ((v >> U(32)) * mm) >> U(32)  # rises with the hash: groups are runs
                new = np.ones(len(v), bool)
                new[1:] = (group[1:] != group[:-1]) | (row[1:] != row[:-1])
                first = np.flatnonzero(new)
                key = mix(np.add.reduceat(mix(v ^ U(0xA5)), first) ^ mix(group[first] + (level[row[first]].astype(U) << U(40))))
            parts.append((row[first], key))
            # with too few groups that have shingles, empty groups count as well
            filled = np.bincount(row[first], minlength=len(n))
            most = self.differ(n, np.minimum(top, n * self.den // self.num))
            for i in np.flatnonzero(goes & (filled <= most)):
                empty = np.setdiff1d(np.arange(m[i]), group[first][row[first] == i].astype(np.int64)).astype(U)
                parts.append((np.full(len(empty), i), mix((empty + (U(int(level[i])) << U(40))) ^ U(0x77777777))))
        if not parts:
            return np.zeros(0, U), np.zeros(len(n) + 1, np.int64)
        row, key = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
        order = np.argsort(row, kind="stable")
        return key[order], np.concatenate([[0], np.cumsum(np.bincount(row, minlength=len(n)))]).astype(np.int64)


def counts(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Count vectors: shingles of each set by GROUPS groups of their low bits."""
    rows = len(bounds) - 1
    row = np.repeat(np.arange(rows), np.diff(bounds))
    return np.bincount(row * GROUPS + (values & U(GROUPS - 1)).astype(np.int64), minlength=rows * GROUPS).reshape(rows, GROUPS).clip(max=255).astype(np.uint8)


def set_ids(values: np.ndarray, bounds: np.ndarray, seed: int = 0) -> np.ndarray:
    """A 64-bit name for each set, from all its members; other seeds give
    independent names."""
    with np.errstate(over="ignore"):
        sums = np.concatenate([np.zeros(1, U), np.cumsum(mix(values ^ mix(np.array([BASE + seed], U))))])
        total = sums[bounds[1:]] - sums[bounds[:-1]]
        return mix(total + np.diff(bounds).astype(U) * U(0xD6E8FEB86659FD93)).view(np.int64)


def overlap_bound(a: np.ndarray, b: np.ndarray, n_a: np.ndarray, n_b: np.ndarray) -> np.ndarray:
    """Most shingles that sets with these count vectors and sizes can share."""
    total = lambda v: v.sum(-1, dtype=np.int64)
    return total(np.minimum(a, b)) + np.minimum(n_a - total(a), n_b - total(b))


class CountTree:
    """R-tree of count vectors, packed by size and by count. ``levels`` go from
    the points up to one root; a node is (upper corner, most that its points
    have beyond their vectors, least and greatest size)."""

    def __init__(self, vectors: np.ndarray, size: np.ndarray):
        self.order = np.lexsort((vectors[:, 1], vectors[:, 0], size))
        v, n = vectors[self.order], size[self.order]
        level = (v, n - v.sum(1, dtype=np.int64), n, n)
        self.levels = [level]
        while len(level[0]) > 1:
            starts = np.arange(0, len(level[0]), LEAF)
            level = tuple(f.reduceat(x, starts) for f, x in zip((np.maximum, np.maximum, np.minimum, np.maximum), level, strict=True))
            self.levels.append(level)

    def children(self, height: int, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place in ``nodes``, child) of all children one level down."""
        first = nodes * LEAF
        many = np.minimum(first + LEAF, len(self.levels[height - 1][0])) - first
        return np.repeat(np.arange(len(nodes)), many), ragged(first, many)

    def near(self, height: int, a: np.ndarray, b: np.ndarray, plan: Plan) -> np.ndarray:
        """Which pairs of nodes of a level may hold a pair that is similar."""
        corner, extra, low, high = self.levels[height]
        keep = (low[a] * plan.num <= high[b] * plan.den) & (low[b] * plan.num <= high[a] * plan.den)
        for at in range(0, len(keep), 4096):
            part = np.flatnonzero(keep[at : at + 4096]) + at
            x, y = a[part], b[part]
            bound = np.minimum(corner[x], corner[y]).sum(1, dtype=np.int64) + np.minimum(extra[x], extra[y])
            keep[part] = plan.enough(bound, low[x], low[y])
        return keep


def rtree_pairs(vectors: np.ndarray, size: np.ndarray, plan: Plan, most: int = 1 << 16) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of points whose count vectors allow the similarity: the tree is
    joined with itself from the root down, at most about ``most`` pairs of nodes
    at a time."""
    tree = CountTree(vectors, size)
    stack = [(len(tree.levels) - 1, np.zeros(1, np.int64), np.zeros(1, np.int64))]
    while stack:
        height, a, b = stack.pop()
        if not height:
            yield tree.order[a], tree.order[b]
            continue
        if len(a) > most // LEAF**2 and len(a) > 1:
            half = len(a) // 2
            stack += [(height, a[half:], b[half:]), (height, a[:half], b[:half])]
            continue
        pair, x = tree.children(height, a)
        which, y = tree.children(height, b[pair])
        x = x[which]
        once = x < y if height == 1 else x <= y  # of a node with itself each pair once
        x, y = x[once], y[once]
        keep = tree.near(height - 1, x, y, plan)
        if keep.any():
            stack.append((height - 1, x[keep], y[keep]))


def padded(lists: pa.ChunkedArray) -> np.recarray:
    """Lists of up to EARLIER keys as rows, and which of their cells are filled."""
    lists = lists.combine_chunks()
    length = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    filled = np.arange(EARLIER) < length[:, None]
    out = np.zeros(filled.shape, np.int64)
    out[filled] = lists.flatten().to_numpy()
    return np.rec.fromarrays([out, filled], names="key,filled")


def met_before(a: np.recarray, b: np.recarray) -> np.ndarray:
    """Pairs that share one of the earlier places that both rows name. The
    first place that a pair shares has none before it, so it is kept there."""
    out = np.zeros(len(a), bool)
    for at in range(0, len(a), 512):
        x, y = a[at : at + 512, :, None], b[at : at + 512, None, :]
        out[at : at + 512] = ((x["key"] == y["key"]) & x["filled"] & y["filled"]).any((1, 2))
    return out


def _verified(pairs: DataFrame, points: DataFrame, docs: DataFrame, plan: Plan, folder: str, name: str) -> DataFrame:
    """The pairs (a, b) of classes whose sets are similar enough. First by their
    count vectors, then by the sets, read again from one text of each class."""
    for side in ("a", "b"):
        point = points.select(F.col("cls").alias(side), F.struct("doc", "name").alias(f"at_{side}"), F.col("n").alias(f"n_{side}"), F.col("counts").alias(f"c_{side}"))
        pairs = pairs.join(point.hint("merge"), side)

    def bound(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not len(batch):
                continue
            get = lambda c: np.frombuffer(b"".join(batch.column(batch.schema.get_field_index(c)).to_pylist()), np.uint8).reshape(-1, GROUPS)  # noqa: B023, E731
            n_a, n_b = (batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("n_a", "n_b"))
            overlap = overlap_bound(get("c_a"), get("c_b"), n_a, n_b)
            yield batch.select(["a", "b", "at_a", "at_b"]).filter(pa.array(plan.enough(overlap, n_a, n_b)))

    at = "struct<doc:long,name:long>"
    left = materialize(pairs.mapInArrow(bound, f"a long, b long, at_a {at}, at_b {at}"), folder, f"{name}_bound")
    ids = materialize(left.select(F.explode(F.array("at_a.doc", "at_b.doc")).alias("doc")).distinct(), folder, f"{name}_docs")
    width = plan.width

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in slices(batches, "text"):
            values, bounds = word_shingles(data, offsets, width)
            grams = [values[a:b].tobytes() for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(set_ids(values, bounds)), pa.array(grams, pa.binary())], ["doc", "name", "grams"])

    # an id may have several texts: the set's name tells which is meant
    grams = may_hold(docs, ids, "doc", "doc long, text string").mapInArrow(sets, "doc long, name long, grams binary")
    grams = materialize(grams, folder, f"{name}_sets")
    both = left.select("a", "b", *[F.col(f"at_{side}.{f}").alias(f"{f}_{side}") for side in "ab" for f in ("doc", "name")])
    for side in ("a", "b"):
        own = grams.select(F.col("doc").alias("own_doc"), F.col("name").alias("own_name"), F.col("grams").alias(f"g_{side}")).hint("merge")
        both = both.join(own, (F.col(f"name_{side}") == F.col("own_name")) & F.col(f"doc_{side}").eqNullSafe(F.col("own_doc"))).drop("own_doc", "own_name")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ga, gb = batch.column(2).to_pylist(), batch.column(3).to_pylist()
            keep = []
            for x, y in zip(ga, gb, strict=True):
                x, y = np.frombuffer(x, U), np.frombuffer(y, U)
                same = np.searchsorted(x, y, "left")
                same = int((x[np.minimum(same, len(x) - 1)] == y).sum()) if len(x) else 0
                keep.append(bool(plan.enough(same, len(x), len(y))) and same > 0)
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    out = materialize(both.select("a", "b", "g_a", "g_b").mapInArrow(compare, "a long, b long").distinct(), folder, name)
    discard(out.sparkSession, folder, f"{name}_bound", f"{name}_sets", f"{name}_docs")
    return out


def _classes(docs: DataFrame, plan: Plan, folder: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(sets, points, places): rows (doc, name, cls, n, counts, keys) of all
    texts, one row (cls, doc, name, n, copies, counts) of each class, and the
    keys that several classes share, with the least and the greatest of them."""

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, data, offsets in slices(batches, "text"):
            values, bounds = word_shingles(data, offsets, plan.width)
            keys, ends = plan.keys(values, bounds)
            vectors = counts(values, bounds)
            yield pa.RecordBatch.from_arrays([
                batch.column(0), pa.array(set_ids(values, bounds)), pa.array(set_ids(values, bounds, 1)), pa.array(np.diff(bounds)),
                pa.array([v.tobytes() for v in vectors], pa.binary()),
                pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(keys.view(np.int64))),
            ], ["doc", "name", "other", "n", "counts", "keys"])

    sets = materialize(docs.mapInArrow(describe, "doc long, name long, other long, n long, counts binary, keys array<long>"), folder, "sets")
    named = materialize(sets.where("n > 0").groupBy("name", "other").agg(F.min("doc").alias("doc"), F.max("n").alias("n"), F.count("*").alias("copies")), folder, "named")
    # sets of one name that the other 64 bits tell apart: next to none
    clash = materialize(named.groupBy("name").agg(F.count("*").alias("k")).where("k > 1").select("name", F.lit(True).alias("clash")), folder, "clash")
    if clash.count():
        own = F.when(F.col("clash"), F.xxhash64("other", "name")).otherwise(F.col("name"))
        sets, named = (df.join(clash, "name", "left").withColumn("cls", own).drop("clash") for df in (sets, named))
    else:
        sets, named = (df.withColumn("cls", F.col("name")) for df in (sets, named))
    vectors = sets.select(F.col("cls").alias("own_cls"), F.col("doc").alias("own_doc"), "counts").hint("merge")
    points = named.join(vectors, (F.col("cls") == F.col("own_cls")) & F.col("doc").eqNullSafe(F.col("own_doc"))).dropDuplicates(["cls"])
    points = materialize(points.select("cls", "doc", "name", "n", "copies", "counts"), folder, "points")
    meet = sets.select("cls", F.explode("keys").alias("key"))
    places = meet.groupBy("key").agg(F.min("cls").alias("hub"), F.max("cls").alias("rim")).where("hub <> rim")
    return sets, points, materialize(places, folder, "places")


def _members(sets: DataFrame, places: DataFrame, folder: str) -> DataFrame:
    """(key, cls, hub, rim) of the classes of each place."""
    meet = sets.select("cls", F.explode("keys").alias("key"))
    live = may_hold(meet, places, "key", "cls long, key long").distinct()
    return materialize(live.join(places.hint("merge"), "key"), folder, "members")


def _searched(own: DataFrame, mixed: DataFrame, points: DataFrame, plan: Plan, block: int) -> DataFrame:
    """Pairs (a, b) of classes of different components that an R-tree of their
    place lets through. ``own`` is (cls, key, component), ``mixed`` (key, blocks)."""
    rest = own.join(mixed.hint("merge"), "key")
    before = Window.partitionBy("cls").orderBy("key").rowsBetween(-EARLIER, -1)
    rest = rest.withColumn("earlier", F.collect_list("key").over(before)).join(points.select("cls", "n", "counts").hint("merge"), "cls")
    i, j = F.pmod(F.xxhash64("cls"), F.col("blocks")).cast("int"), F.col("j")
    tiles = rest.withColumn("j", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select("key", F.least(i, j).alias("lo"), F.greatest(i, j).alias("hi"), "cls", "component", "n", "counts", "earlier")
    rows = mixed.agg(F.sum(F.col("blocks") * F.col("blocks") * block)).first()[0] or 0
    buckets = max(1, int(rows) // 20_000)

    def search(table: pa.Table) -> pa.Table:
        cls, comp_, n, key, lo, hi = (table[c].to_numpy() for c in ("cls", "component", "n", "key", "lo", "hi"))
        vectors = np.frombuffer(b"".join(table["counts"].to_pylist()), np.uint8).reshape(-1, GROUPS)
        seen = padded(table["earlier"])
        order = np.lexsort((hi, lo, key))
        cut = np.flatnonzero((np.diff(key[order]) != 0) | (np.diff(lo[order]) != 0) | (np.diff(hi[order]) != 0)) + 1
        out = [np.zeros((2, 0), np.int64)]
        for place in np.split(order, cut):
            if len(place) > 1 and (comp_[place] != comp_[place[0]]).any():
                for a, b in rtree_pairs(vectors[place], n[place], plan):
                    apart = comp_[place[a]] != comp_[place[b]]
                    a, b = place[a[apart]], place[b[apart]]
                    new = ~met_before(seen[a], seen[b])
                    out.append(np.stack([cls[a[new]], cls[b[new]]]))
        pairs = np.unique(np.sort(np.concatenate(out, 1), axis=0), axis=1)
        return pa.table({"a": pairs[0], "b": pairs[1]})

    bucket = F.pmod(F.xxhash64("key", "lo", "hi"), F.lit(buckets)).alias("bucket")
    return tiles.groupBy(bucket).applyInArrow(search, "a long, b long").distinct()


def _docs(df: DataFrame, key: str, text: str) -> DataFrame:
    return df.select(F.col(key).cast("long").alias("doc"), F.coalesce(F.col(text), F.lit("")).alias("text"))


def _least(rows: DataFrame, folder: str) -> DataFrame:
    """``rows`` with the least id of each row's component."""
    least = materialize(rows.where("component is not null").groupBy("component").agg(F.min("doc").alias("least")), folder, "least")
    return rows.join(least.hint("merge"), "component", "left")


def jaccard_groups(df: DataFrame, plan: Plan | None = None, key: str = "doc_id", text: str = "text", block: int = 512, more_stars: int = 0) -> DataFrame:
    """(key, n_shingles, component_id) for each row of ``df``."""
    plan = plan or Plan()
    folder, docs = workspace(df.sparkSession), _docs(df, key, text)
    sets, points, places = _classes(docs, plan, folder)
    members = _members(sets, places, folder)
    centres = members.select("cls", F.explode(F.array("hub", "rim")).alias("hub")).where("cls <> hub")
    stars = materialize(centres.select(F.least("cls", "hub").alias("a"), F.greatest("cls", "hub").alias("b")).distinct(), folder, "stars")
    links, tested = _verified(stars, points, docs, plan, folder, "links"), stars
    comp = materialize(components(links, folder), folder, "comp0")
    turn = 0
    while True:
        # members under their components, and the places that still hold several
        own = materialize(members.select("cls", "key").join(comp.withColumnRenamed("node", "cls").hint("merge"), "cls", "left").withColumn("component", F.coalesce("component", "cls")), folder, f"own{turn}")
        picks = [F.min(F.struct(F.xxhash64("cls", F.lit(2 * turn + k)), "cls", "component")).alias(f"pick{k}") for k in (0, 1)]
        mixed = own.groupBy("key").agg(F.min("component").alias("x"), F.max("component").alias("y"), F.count("*").alias("size"), *picks).where("x <> y and size > 2")
        mixed = materialize(mixed.select("key", F.ceil(F.col("size") / block).cast("int").alias("blocks"), F.array("pick0", "pick1").alias("hubs")), folder, f"mixed{turn}")
        if turn == more_stars:
            break
        turn += 1
        more = own.join(mixed.hint("merge"), "key").select("cls", "component", F.explode("hubs").alias("hub")).where("component <> hub.component").select(F.least("cls", "hub.cls").alias("a"), F.greatest("cls", "hub.cls").alias("b")).distinct()
        more = materialize(more.join(tested.hint("merge"), ["a", "b"], "left_anti"), folder, f"stars{turn}")
        if not more.limit(1).count():
            break
        tested = tested.unionAll(more)
        links = links.unionAll(_verified(more, points, docs, plan, folder, f"links{turn}"))
        comp = materialize(components(links, folder), folder, f"comp{turn}")
    found = _searched(own, mixed.drop("hubs"), points, plan, block)
    found = materialize(found.join(tested.hint("merge"), ["a", "b"], "left_anti"), folder, "found")
    discard(df.sparkSession, folder, *[f"own{k}" for k in range(turn + 1)], "members", "places")
    if found.limit(1).count():
        more = _verified(found, points, docs, plan, folder, "more")
        comp = materialize(components(links.unionAll(more), folder), folder, "comp")
    rows = sets.select("doc", "cls", "n").join(comp.withColumnRenamed("node", "cls").hint("merge"), "cls", "left")
    rows = materialize(rows.select("doc", "n", F.when(F.col("n") > 0, F.coalesce("component", "cls")).alias("component")), folder, "rows")
    return _least(rows, folder).select(F.col("doc").alias(key), F.col("n").alias("n_shingles"), F.coalesce("least", "doc").alias("component_id"))


def jaccard_links(df: DataFrame, plan: Plan | None = None, key: str = "doc_id", text: str = "text", block: int = 512) -> tuple[DataFrame, DataFrame]:
    """All links. The first table is (key, cls, n_shingles, n_links,
    component_id) of each row: its class (null without words), and with how
    many other rows it is linked, copies counted one by one. The second is
    (a, b), every verified pair of different classes once."""
    plan = plan or Plan()
    folder, docs = workspace(df.sparkSession), _docs(df, key, text)
    sets, points, places = _classes(docs, plan, folder)
    own = _members(sets, places, folder).select("cls", "key", F.col("cls").alias("component"))
    mixed = materialize(own.groupBy("key").agg(F.ceil(F.count("*") / block).cast("int").alias("blocks")), folder, "mixed")
    found = materialize(_searched(own, mixed, points, plan, block), folder, "found")
    pairs = _verified(found, points, docs, plan, folder, "links")
    comp = materialize(components(pairs, folder), folder, "comp")
    ends = pairs.select("a", "b").unionAll(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
    degree = ends.join(points.select(F.col("cls").alias("b"), "copies").hint("merge"), "b").groupBy(F.col("a").alias("cls")).agg(F.sum("copies").alias("near"))
    degree = points.select("cls", "copies").join(degree.hint("merge"), "cls", "left").select("cls", (F.col("copies") - 1 + F.coalesce("near", F.lit(0))).alias("n_links"))
    rows = sets.select("doc", "n", F.when(F.col("n") > 0, F.col("cls")).alias("cls"))
    rows = rows.join(degree.hint("merge"), "cls", "left").join(comp.withColumnRenamed("node", "cls").hint("merge"), "cls", "left")
    rows = materialize(rows.withColumn("component", F.coalesce("component", "cls")), folder, "rows")
    out = _least(rows, folder).select(F.col("doc").alias(key), "cls", F.col("n").alias("n_shingles"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("least", "doc").alias("component_id"))
    return out, pairs


def keep_first(df: DataFrame, plan: Plan, key: str = "doc_id") -> DataFrame:
    """One row of each group of ``df``, all columns: that of the least id, null
    last, and of rows with one id that of the least row hash.

    The nodes are rows, named by a 64-bit hash of all their columns, and not
    ids: an id may be null or carry several texts, which need not be in one
    group. Rows that agree in every column are one row, with or without words;
    other rows without words all stay. Of the texts only those of rows that
    repeat are shuffled."""
    folder, columns = workspace(df.sparkSession), df.columns
    # the hash passes over nulls, so that which columns are null is added
    df = df.withColumn("_row", F.xxhash64(*[F.col(c).isNull() for c in columns], *columns))
    ids = materialize(df.groupBy("_row").agg(F.min(key).alias("id"), F.count("*").alias("n")), folder, "ids")
    repeated = materialize(ids.where("n > 1").select(F.col("_row").alias("_again")), folder, "repeated")
    n = repeated.count()
    if n:
        fit = F.broadcast(repeated) if n <= 1_000_000 else repeated.hint("merge")
        same = df["_row"] == repeated["_again"]
        once = materialize(df.join(fit, same, "left_semi").dropDuplicates(["_row"]), folder, "once")
        df = df.join(fit, same, "left_anti").unionAll(once)
    groups = materialize(jaccard_groups(df, plan, "_row").select("_row", F.col("component_id").alias("component")).join(ids.select("_row", "id").hint("merge"), "_row"), folder, "groups")
    least = groups.groupBy("component").agg(F.min(F.struct(F.col("id").isNull(), "id", "_row")).getField("_row").alias("first"), F.count("*").alias("size")).where("size > 1")
    least = materialize(least, folder, "least")
    gone = materialize(groups.join(least.hint("merge"), "component").where("_row <> first").select(F.col("_row").alias("_gone")), folder, "gone")
    few = gone.count() <= 1_000_000
    return df.join(F.broadcast(gone) if few else gone.hint("merge"), df["_row"] == gone["_gone"], "left_anti").select(*columns)
