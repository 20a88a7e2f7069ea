"""Shared parts of the corpus operators: tables in the shared folder, hashing
of Arrow buffers, Bloom filters of a checked size and connected components."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shared import remove, workspace  # noqa: F401 - the operators take it from here

U = np.uint64
#: Odd multiplier that tells the two halves of a string apart.
BASE = 0x9E3779B97F4A7C15


def materialize(df: DataFrame, folder: str, name: str) -> DataFrame:
    """Write a table into the shared folder and read it back. This cuts the
    lineage, and a lost executor costs no more than the tasks it was running."""
    path = f"{folder}/{name}"
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(spark: SparkSession, folder: str, *names: str) -> None:
    """Delete tables of a workspace that no later plan reads."""
    for name in names:
        remove(spark, f"{folder}/{name}")


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over all 64 output bits."""
    with np.errstate(over="ignore"):
        x = x ^ (x >> U(30))
        x *= U(0xBF58476D1CE4E5B9)
        x ^= x >> U(27)
        x *= U(0x94D049BB133111EB)
        x ^= x >> U(31)
        return x


def span_hash(data: np.ndarray, start: np.ndarray, stop: np.ndarray, seed: int = 0x51) -> np.ndarray:
    """Hash of each byte string data[start:stop], none of them empty. Each byte
    is mixed with its place in the string before the sum, so that strings which
    repeat themselves are as good as others; different seeds are independent."""
    size = stop - start
    ends = np.cumsum(size)
    place = np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - size, size)
    with np.errstate(over="ignore"):
        value = mix((place.astype(U) << U(8)) + data[place + np.repeat(start, size)] + (U(seed) << U(48)))
        total = np.add.reduceat(value, ends - size) if len(size) else np.zeros(0, U)
        return mix(total + size.astype(U) * U(BASE))


def gram_hashes(data: np.ndarray, gram: int) -> np.ndarray:
    """Hash of the ``gram`` bytes from each place on; ``gram`` is a power of two
    from 8 on. Halves are mixed into wholes, so no string cancels out."""
    out = np.empty(max(len(data) - 7, 0), U)
    for r in range(min(8, len(out))):
        part = data[r : r + (len(data) - r) // 8 * 8]
        out[r::8] = np.frombuffer(part.tobytes(), "<u8")
    out, width = mix(out + U(0x2545F4914F6CDD1D)), 8
    with np.errstate(over="ignore"):
        while width < gram:
            out = mix(out[:-width] * U(BASE) + out[width:]) if len(out) > width else out[:0]
            width *= 2
    return out


def column_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column, and where each row starts in them (one
    more for the end). Null counts as empty."""
    column = column.fill_null("") if column.null_count else column
    large = pa.types.is_large_string(column.type)
    offsets = np.frombuffer(column.buffers()[1], np.int64 if large else np.int32)
    offsets = offsets[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = column.buffers()[2]
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(batches: Iterator[pa.RecordBatch], text: str, limit: int = 500_000, rows: int = 1 << 20) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Cut batches into runs of at most ``rows`` rows and about ``limit`` bytes
    of text, so that the work space of a task is bounded; a longer row comes
    alone and whole."""
    for batch in batches:
        at, column = 0, batch.column(batch.schema.get_field_index(text))
        data, offsets = column_bytes(column)
        while at < len(batch):
            to = min(at + rows, max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1))
            yield batch.slice(at, to - at), data[offsets[at] : offsets[to]], offsets[at : to + 1] - offsets[at]
            at = to
        del column, data
        pa.default_memory_pool().release_unused()


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Concatenation of the ranges starts[i] .. starts[i] + lengths[i]."""
    ends = np.cumsum(lengths)
    if not len(ends) or not ends[-1]:
        return np.zeros(0, np.int64)
    return np.arange(ends[-1]) + np.repeat(starts - (ends - lengths), lengths)


#: ASCII lower case, and the six characters of ASCII white space.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True


def word_shingles(data: np.ndarray, offsets: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the distinct word shingles of each row, sorted within the row,
    and the row bounds. Words are runs without ASCII white space, A-Z in lower
    case. A row of 1 to width - 1 words gives its whole sequence as one."""
    rows = len(offsets) - 1
    letters = ~SPACE[data]
    first = letters.copy()
    first[1:] &= ~letters[:-1]
    inner = offsets[(offsets > 0) & (offsets < len(data))]
    first[inner] = letters[inner]
    last = letters.copy()
    last[:-1] &= ~letters[1:]
    last[inner - 1] = letters[inner - 1]
    start, stop = np.flatnonzero(first), np.flatnonzero(last) + 1
    words = span_hash(LOWER[data], start, stop)
    row = np.searchsorted(offsets, start, "right") - 1
    held = np.bincount(row, minlength=rows)
    begin = np.cumsum(held) - held
    shingles = np.maximum(held - width + 1, np.minimum(held, 1))
    at = ragged(begin, shingles)
    which = np.repeat(np.arange(rows), shingles)
    value = np.full(len(at), 0x51, U)
    end = (begin + held)[which]
    with np.errstate(over="ignore"):
        for k in range(width):
            inside = at + k < end
            value = mix(value * U(BASE) + np.where(inside, words[np.minimum(at + k, max(len(words) - 1, 0))] if len(words) else U(0), U(k)))
    order = np.lexsort((value, which))
    value, which = value[order], which[order]
    keep = np.ones(len(value), bool)
    keep[1:] = (value[1:] != value[:-1]) | (which[1:] != which[:-1])
    value, which = value[keep], which[keep]
    return value, np.concatenate([[0], np.cumsum(np.bincount(which, minlength=rows))]).astype(np.int64)


#: Most keys of a Bloom filter: at 8 bits or more each, 32 MB to broadcast.
FILTER_KEYS = 1 << 25


class Bloom:
    """Two probes into a bit table, by the 64-bit hash of a key."""

    def __init__(self, words: np.ndarray):
        self.words = words

    def holds(self, h: np.ndarray) -> np.ndarray:
        """Mask of the hashes that may be in it (none that is in it is missed)."""
        mask = U((len(self.words) << 6) - 1)
        hit = lambda p: (self.words[p >> U(6)] >> (p & U(63))) & U(1) != 0
        return hit(h & mask) & hit((h >> U(32)) & mask)


def bloom(df: DataFrame, column: str, most: int = FILTER_KEYS) -> Bloom | None:
    """Filter of a long column of a written table, sized from its count at 8 to
    16 bits a row, or None beyond ``most`` rows: then callers go without it or
    join instead. Its rows' hash is ``xxhash64(column)``."""
    keys = df.count()
    if keys > most:
        return None
    bits = max(16, int(8 * keys).bit_length())
    h = F.xxhash64(F.col(column))
    mask = (1 << bits) - 1
    probes = F.explode(F.array(h.bitwiseAND(F.lit(mask)), F.shiftrightunsigned(h, 32).bitwiseAND(F.lit(mask))))
    words = (
        df.select(probes.alias("p")).groupBy(F.shiftright("p", 6).alias("w"))
        .agg(F.bit_or(F.expr("shiftleft(1L, cast(p & 63 as int))")).alias("b"))
    )
    out = np.zeros(1 << (bits - 6), U)
    got = words.toArrow()
    out[got["w"].to_numpy()] = got["b"].to_numpy().view(U)
    return Bloom(out)


def may_hold(rows: DataFrame, keys: DataFrame, column: str, schema: str) -> DataFrame:
    """The columns of ``schema`` of the rows whose ``column`` may be among that
    of ``keys``: a narrow pass that leaves most others out before a join. Beyond
    the filter's bound all rows; the join is then the only test."""
    names = [part.split()[0] for part in schema.split(", ")]
    made = bloom(keys, column)
    if made is None:
        return rows.select(*names)
    shared = rows.sparkSession.sparkContext.broadcast(made)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.select(names).filter(pa.array(shared.value.holds(batch.column(len(names)).to_numpy().view(U))))

    return rows.select(*names, F.xxhash64(column).alias("_h")).mapInArrow(run, schema)


def components(edges: DataFrame, folder: str, src: str = "a", dst: str = "b") -> DataFrame:
    """(node, component): for every node of an edge its component's least node.

    Each round, the larger neighbours of a node move to its least neighbour
    (large star), then the smaller ones do (small star). The rounds go on until
    only stars are left, however many that takes. Least neighbours are written before they are
    joined, so that a node with very many edges can be split by the join.
    Null ends and loops are ignored."""
    spark = edges.sparkSession
    now = edges.select(F.greatest(src, dst).alias("a"), F.least(src, dst).alias("b")).where("a <> b and a is not null and b is not null").distinct()
    now = materialize(now, folder, "cc0")
    if _settled(now):
        return _labels(now)
    for turn in count(1):
        both = now.select("a", "b").unionAll(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = materialize(both.groupBy("a").agg(F.min("b").alias("m")), folder, f"ccm{turn}")
        large = both.join(least.hint("merge"), "a").where("b > a").select(F.col("b").alias("a"), F.least("a", "m").alias("b")).distinct()
        large = materialize(large, folder, f"ccl{turn}")
        least = materialize(large.groupBy("a").agg(F.min("b").alias("m")), folder, f"ccs{turn}")
        small = large.join(least.hint("merge"), "a").select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.greatest("b", "m").alias("a"), F.least("b", "m").alias("b")))).alias("e")).select("e.a", "e.b").where("a <> b").distinct()
        nxt = materialize(small, folder, f"cc{turn}")
        discard(spark, folder, f"cc{turn - 1}", f"ccm{turn}", f"ccl{turn}", f"ccs{turn}")
        now = nxt
        if _settled(now):
            break
    return _labels(now)


def _labels(now: DataFrame) -> DataFrame:
    roots = now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct()
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionAll(roots)


def _settled(now: DataFrame) -> bool:
    """Whether every edge joins a node that has no other edge to its root."""
    ends = now.select(F.explode(F.array(F.struct(F.col("a").alias("n"), F.lit(1).alias("up"), F.lit(0).alias("down")), F.struct(F.col("b").alias("n"), F.lit(0).alias("up"), F.lit(1).alias("down")))).alias("e")).select("e.*")
    busy = ends.groupBy("n").agg(F.sum("up").alias("up"), F.max("down").alias("down")).where("up > 1 or up > 0 and down > 0")
    return not busy.agg(F.count("*")).first()[0]


def forest(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Mask of edges that join two trees when added in order; the other edges
    add no reachability."""
    names, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    parent = list(range(len(names)))

    def top(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    keep = np.zeros(len(a), bool)
    for i, (x, y) in enumerate(zip(ends[: len(a)].tolist(), ends[len(a) :].tolist(), strict=True)):
        if (p := top(x)) != (q := top(y)):
            parent[max(p, q)] = min(p, q)
            keep[i] = True
    return keep
