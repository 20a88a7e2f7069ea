"""Removal of byte strings of ``length`` (200) bytes that occur twice or more.

A Burrows-Wheeler transform of the whole corpus fits no machine, so the corpus
is cut into independent ranges of its suffix order. Every window of 200 bytes
has one anchor: the least of the hashes of its 64-byte strings (leftmost of
equals). Equal windows have equal anchors, hence only windows of one anchor
string must be compared, and those are an interval of the suffix order: the
suffixes that start with the anchor string.

1. For each run of windows with one anchor: (anchor hash, hash of the run's
   bytes, place). Anchors seen once are dropped by an aggregate.
2. Runs whose bytes occur twice are covered as they stand; anchor and bytes are
   told apart by 128 bits of hash. Only distinct runs of anchors that have
   several are left: the edges of repeats.
3. In each anchor's interval, the texts right of the anchor are sorted with
   their common prefixes. Breadth first, the interval is extended backwards one
   byte at a time (a step of the transform's last-to-first mapping): after k
   steps the intervals are the strings of k bytes, the anchor and what is right
   of it, cut to 200 bytes. An interval of one suffix is not extended, and the
   extension ends at 200 bytes. An interval of two or more is a repeat.
4. An interval of more than ``group_limit`` distinct runs (the edge of a passage
   that very many documents share) is too large for one task. There the strings
   that the extension would end at are named by their hashes, all at once, and
   counted by an aggregate, which combines before it shuffles and which no key
   can overload. Both ways give the same ranges.

Texts are compared as UTF-8 bytes within documents; null is empty. Texts move
only for documents that have something to compare or to remove (a Bloom filter
of ids lets these through; beyond its bound a join does). Rows that repeat in
full count as copies; rows with one id must have one text. A null id stays null;
within, a hash of the text stands for it. Other columns are left behind.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BASE, U, bloom, column_bytes, discard, gram_hashes, materialize, may_hold, mix, slices, workspace

GRAM = 64


def anchored_runs(data: np.ndarray, offsets: np.ndarray, length: int, gram: int):
    """(row, first window, windows, anchor's place in the run, anchor hash, hash
    of the run's bytes) of all runs; places count from the row's start."""
    if len(data) < length:
        return [np.zeros(0, np.int64)] * 4 + [np.zeros(0, U)] * 2
    grams = gram_hashes(data, gram)
    # high half: hash; low half: place, so that the least is the leftmost of equals
    low = (grams & U(0xFFFFFFFF00000000)) | np.arange(len(grams), dtype=U)
    span, width = length - gram + 1, 1
    while width * 2 <= span:
        low = np.minimum(low[:-width], low[width:])
        width *= 2
    if width < span:
        low = np.minimum(low[: len(low) - (span - width)], low[span - width :])
    anchor = (low & U(0xFFFFFFFF)).astype(np.int64)
    row = np.searchsorted(offsets, np.arange(len(anchor)), "right") - 1
    inside = np.arange(len(anchor)) + length <= offsets[row + 1]
    begin = inside.copy()
    begin[1:] &= (anchor[1:] != anchor[:-1]) | ~inside[:-1] | (row[1:] != row[:-1])
    start = np.flatnonzero(begin)
    end = inside.copy()
    end[:-1] &= begin[1:] | ~inside[1:]
    count = np.flatnonzero(end) + 1 - start
    body = long_hash(grams, start, start + count - 1 + length, gram, 2 * length - gram)
    return row[start], start - offsets[row[start]], count, anchor[start] - start, grams[anchor[start]], body


def long_hash(grams: np.ndarray, start: np.ndarray, stop: np.ndarray, gram: int, most: int) -> np.ndarray:
    """Hash of each string start:stop of ``gram`` to ``most`` bytes, from the
    hashes of the grams that cover it."""
    last = stop - start - gram
    out = mix(last.astype(U))
    with np.errstate(over="ignore"):
        for at in range(0, most, gram):
            out = mix(out * U(BASE) + grams[start + np.minimum(at, last)])
    return out


def repeated_windows(anchor: np.ndarray, place: np.ndarray, count: np.ndarray, texts: list[bytes], length: int, gram: int) -> np.ndarray:
    """Mask (runs by windows): which windows occur in another run too. Runs are
    distinct; ``place`` is the anchor's place in the run's text."""
    n, span = len(texts), length - gram + 1
    data = np.frombuffer(b"".join(texts), np.uint8)
    size = np.array([len(t) for t in texts], np.int64)
    base = np.cumsum(size) - size
    out = np.zeros((n, span), bool)
    col = np.arange(length)
    at = (base + place)[:, None] + col
    right = np.where(place[:, None] + col < size[:, None], data[np.minimum(at, len(data) - 1)], 0)
    packed = np.ascontiguousarray(np.pad(right, ((0, 0), (0, -length % 8)))).view(">u8")
    order = np.lexsort((*packed.T[::-1].astype(U), anchor))
    sorted_right, sorted_anchor = right[order], anchor[order]
    same = sorted_right[1:] == sorted_right[:-1]
    prefix = np.where(same.all(1), length, (~same).argmax(1))
    prefix[sorted_anchor[1:] != sorted_anchor[:-1]] = -1
    prefix = np.concatenate([[-1], prefix])
    # names of the backward strings, in suffix order: extended by a byte a step
    where, back = base[order] + place[order], place[order]
    name = np.concatenate([[0], np.cumsum(sorted_anchor[1:] != sorted_anchor[:-1])]).astype(np.int64)
    live = np.arange(n)
    for step in range(span):
        if step:
            live = live[back[live] >= step]
            if not len(live):
                break
            _, name_live, number = np.unique(name[live] * 256 + data[where[live] - step], return_inverse=True, return_counts=True)
            keep = number[name_live] > 1
            live, name_live = live[keep], name_live[keep]
            name[live] = name_live
            if not len(live):
                break
        window = back[live] - step
        group = np.cumsum(prefix < length - step)[live]  # same right part of length - step bytes
        held = (window >= 0) & (window < count[order][live])
        which, number = _pairs(name[live][held], group[held])
        hit = number[which] > 1
        out[order[live[held][hit]], window[held][hit]] = True
    return out


def _pairs(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Number of each pair, and how often each number occurs."""
    _, which, number = np.unique(a * (int(b.max()) + 1 if len(b) else 1) + b, return_inverse=True, return_counts=True)
    return which, number


def _through(df: DataFrame, ids: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """Rows (id, doc, text) whose doc the filter lets through, and the others;
    all and None beyond the filter's bound."""
    made = bloom(ids, "doc")
    if made is None:
        return df.select("id", "doc", "text"), None
    shared = df.sparkSession.sparkContext.broadcast(made)

    def part(inside: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                yield batch.select(["id", "doc", "text"]).filter(pa.array(shared.value.holds(batch.column(3).to_numpy().view(U)) == inside))

        return df.select("id", "doc", "text", F.xxhash64("doc").alias("h")).mapInArrow(run, "id long, doc long, text string")

    return part(True), part(False)


def repeated_ranges(docs: DataFrame, folder: str, length: int = 200, gram: int = GRAM, group_limit: int = 10_000, bucket: int = 10_000) -> DataFrame:
    """(doc, start, stop): byte ranges that together are all bytes covered by a
    string of ``length`` bytes that also starts elsewhere."""
    spark = docs.sparkSession

    def runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, data, offsets in slices(batches, "text"):
            row, start, count, place, anchor, body = anchored_runs(data, offsets, length, gram)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(row)), pa.array(start), pa.array(count.astype(np.int32)), pa.array(place.astype(np.int32)), pa.array(anchor.view(np.int64)), pa.array(body.view(np.int64))], ["doc", "start", "windows", "place", "anchor", "body"])

    occ = materialize(docs.select("doc", "text").mapInArrow(runs, "doc long, start long, windows int, place int, anchor long, body long"), folder, "runs")
    seen = occ.groupBy("anchor").agg(F.count("*").alias("n"), F.min("body").alias("x"), F.max("body").alias("y")).where("n > 1")
    seen = materialize(seen.select("anchor", (F.col("x") == F.col("y")).alias("alike")), folder, "anchors")
    few = may_hold(occ, seen, "anchor", "doc long, start long, windows int, place int, anchor long, body long")
    few = materialize(few.join(seen.hint("merge"), "anchor"), folder, "repeats")
    discard(spark, folder, "runs", "anchors")
    stop = (F.col("start") + F.col("windows") - 1 + length).alias("stop")
    whole = few.where("alike").select("doc", "start", stop)
    edges = few.where("not alike")
    bodies = edges.groupBy("anchor", "body").agg(F.count("*").alias("n"), F.min(F.struct("doc", "start", "windows", "place")).alias("first"))
    bodies = materialize(bodies, folder, "bodies")
    copied = edges.select("doc", "start", "windows", "anchor", "body").join(bodies.where("n > 1").select("anchor", "body").hint("merge"), ["anchor", "body"]).select("doc", "start", stop)
    sizes = materialize(bodies.groupBy("anchor").agg(F.count("*").alias("bodies")), folder, "sizes")
    todo = bodies.join(sizes.hint("merge"), "anchor").select("anchor", "n", "bodies", "first.*")
    todo = materialize(todo, folder, "todo")
    total = todo.count()
    out = whole.unionAll(copied)
    if not total:
        return out
    wanted = materialize(todo.groupBy("doc").agg(F.collect_list(F.struct("start", "windows", "place", "anchor", "n", "bodies")).alias("runs")), folder, "wanted")
    texts, _ = _through(docs, wanted)

    def snippets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["doc", "start", "windows", "place", "anchor", "n", "bodies", "bytes"]
        for batch in batches:
            data, offsets = column_bytes(batch.column(1))
            listed = batch.column(2)
            per = np.diff(np.asarray(listed.offsets))
            row = np.repeat(np.arange(len(batch)), per)
            fields = listed.flatten()
            start, windows = fields.field("start").to_numpy(), fields.field("windows").to_numpy()
            a = offsets[row] + start
            for lo in range(0, len(row), 20_000):
                hi = lo + 20_000
                cut = [data[p:q].tobytes() for p, q in zip(a[lo:hi], (a + windows - 1 + length)[lo:hi], strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(row[lo:hi])), *[fields.field(c)[lo:hi] for c in names[1:7]], pa.array(cut, pa.binary())], names)

    got = texts.join(wanted.hint("merge"), "doc").select("doc", "text", "runs").mapInArrow(snippets, "doc long, start long, windows int, place int, anchor long, n long, bodies long, bytes binary")
    got = materialize(got, folder, "snippets")
    buckets = max(1, -(-total // bucket))

    def extend(table: pa.Table) -> pa.Table:
        anchor, place, windows, start, doc, n = (table[c].to_numpy().astype(np.int64) for c in ("anchor", "place", "windows", "start", "doc", "n"))
        hit = repeated_windows(anchor, place, windows, table["bytes"].to_pylist(), length, gram)
        hit[n > 1] = False  # covered already
        edge = np.diff(np.pad(hit, ((0, 0), (1, 1))).astype(np.int8), axis=1)
        row, a = np.nonzero(edge == 1)
        b = np.nonzero(edge == -1)[1]
        return pa.table({"doc": doc[row], "start": start[row] + a, "stop": start[row] + b - 1 + length})

    # a large interval is a bucket of its own, small ones share one by hash
    own = F.when(F.col("bodies") > bucket // 8, F.xxhash64("anchor")).otherwise(F.pmod(F.xxhash64("anchor", F.lit(1)), F.lit(buckets)))
    small = got.where(F.col("bodies") <= group_limit).groupBy(own.alias("bucket"))
    out = out.unionAll(small.applyInArrow(extend, "doc long, start long, stop long"))
    if sizes.where(F.col("bodies") > group_limit).limit(1).count():
        out = out.unionAll(_by_hashes(got.where(F.col("bodies") > group_limit), folder, length, gram))
    return out


def _by_hashes(rows: DataFrame, folder: str, length: int, gram: int) -> DataFrame:
    """Ranges of the windows that occur in several runs of their anchor."""

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, len(batch), 2000):
                part = batch.slice(lo, 2000)
                texts, count = part.column(7).to_pylist(), part.column(2).to_numpy().astype(np.int64)
                base = np.cumsum([0, *[len(t) for t in texts]])[:-1]
                row = np.repeat(np.arange(len(part)), count)
                j = np.arange(len(row)) - (np.cumsum(count) - count)[row]
                at = base[row] + j
                value = long_hash(gram_hashes(np.frombuffer(b"".join(texts), np.uint8), gram), at, at + length, gram, length)
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(row)), pa.array(part.column(1).to_numpy()[row] + j), part.column(4).take(pa.array(row)), pa.array(value.view(np.int64))], ["doc", "start", "anchor", "window"])

    each = materialize(rows.mapInArrow(windows, "doc long, start long, anchor long, window long"), folder, "windows")
    twice = materialize(each.groupBy("anchor", "window").agg(F.count("*").alias("n")).where("n > 1").select("anchor", "window"), folder, "twice")
    return each.join(twice.hint("merge"), ["anchor", "window"]).select("doc", "start", (F.col("start") + length).alias("stop"))


def remove_repeats(df: DataFrame, length: int = 200, key: str = "doc_id", text: str = "text", keep_text: bool = False, **options) -> DataFrame:
    """(key, n_bytes, n_removed, n_spans, kept_sha256) and, with ``keep_text``,
    ``kept``: the bytes that are left."""
    folder = workspace(df.sparkSession)
    body = F.coalesce(F.col(text), F.lit(""))
    docs = df.select(F.col(key).cast("long").alias("id"), F.coalesce(F.col(key).cast("long"), F.xxhash64(body)).alias("doc"), body.alias("text"))
    ranges = repeated_ranges(docs, folder, length, **options)
    per = materialize(ranges.groupBy("doc").agg(F.collect_list(F.struct("start", "stop")).alias("ranges")), folder, "ranges")
    touched, rest = _through(docs, per)
    schema = "id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * keep_text

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = column_bytes(batch.column(1))
            out: list[list] = [[] for _ in range(4 + keep_text)]
            for i in range(len(batch)):
                body = data[offsets[i] : offsets[i + 1]]
                value = batch.column(2)[i]
                kept, removed, spans = body, 0, 0
                if value.is_valid:
                    flat = value.values
                    a, b = (np.asarray(flat.field(c)) for c in ("start", "stop"))
                    edge = np.zeros(len(body) + 1, np.int64)
                    np.add.at(edge, a, 1)
                    np.add.at(edge, b, -1)
                    gone = np.cumsum(edge[:-1]) > 0
                    kept, removed = body[~gone], int(gone.sum())
                    spans = int(gone[:1].sum() + (gone[1:] & ~gone[:-1]).sum())
                kept = kept.tobytes()
                for column, v in zip(out, (len(body), removed, spans, hashlib.sha256(kept).hexdigest(), kept), strict=False):
                    column.append(v)
            kinds = [pa.int64()] * 3 + [pa.string(), pa.binary()][: 1 + keep_text]
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(c, k) for c, k in zip(out, kinds, strict=True)]], ["id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"][: 5 + keep_text])

    done = touched.join(per.hint("merge"), "doc", "left").select("id", "text", "ranges").mapInArrow(cut, schema)
    if rest is None:
        return done.withColumnRenamed("id", key)
    as_is = rest.select("id", F.octet_length("text").cast("long").alias("n_bytes"), F.lit(0).cast("long").alias("n_removed"), F.lit(0).cast("long").alias("n_spans"), F.sha2("text", 256).alias("kept_sha256"), *[F.col("text").cast("binary").alias("kept")] * keep_text)
    return done.unionAll(as_is).withColumnRenamed("id", key)
