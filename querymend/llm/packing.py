"""Packing token sequences by vector best fit.

A piece asks for a vector of three: its tokens, one document, and its attention
cost (the square of its tokens). A bin (sequence) has a capacity for each. In
falling order of length every piece goes to the bin in which it fits best: the
least norm of what remains, or the greatest weighted dot product of demand and
remainder, under every constraint.

All three demands follow from the length, so the choice needs the counts of
the lengths only, at most ``capacity`` numbers whatever the corpus. The driver
packs these counts: bins in the same state are one row with a multiplicity, a
placement puts a run of pieces of one length on a run of bins. The runs are
broadcast (bounded by lengths and states, not by documents), and every piece
finds its bin from its rank among the pieces of its length. Ranks come from
counts by (length, salt); a length has a salt for each ``group`` of its pieces,
so neither empty texts nor full pieces gather in a task, and the driver gets one
count for so many pieces.

The distinct words of a batch are encoded once and kept under a hash, which only
sorts them: a word is taken for a known one if its bytes are the same. Added
tokens of the vocabulary file that a text spells out are their ids, as the
tokenizer has it; the text on their two sides is encoded apart.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, ragged, slices, span_hash, workspace

PIECES = "piece int, start long, length long, ids_crc32 long"


#: ASCII white space of the splitting pattern, and the characters beyond ASCII.
BLANK = np.zeros(256, bool)
BLANK[[9, 10, 11, 12, 13, 28, 29, 30, 31, 32]] = True
WIDE_BLANKS = [chr(c).encode() for c in (0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)]


def blanks(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Masks of the bytes at which white space ends, and at which it starts."""
    ends, starts = BLANK[data].copy(), BLANK[data].copy()
    for lead in {w[0] for w in WIDE_BLANKS}:
        at = np.flatnonzero(data == lead)
        for w in (w for w in WIDE_BLANKS if w[0] == lead):
            spot = at[at + len(w) <= len(data)]
            for k in range(1, len(w)):
                spot = spot[data[spot + k] == w[k]]
            starts[spot] = True
            ends[spot + len(w) - 1] = True
    return ends, starts


class WordTokenizer:
    """Byte-level BPE of a public vocabulary file, with a store of known words.

    A space between two characters that are no white space starts a new word of
    the vocabulary's splitting pattern, so text is cut there first."""

    def __init__(self, path: str, pattern: str, keep: int = 200_000):
        import tiktoken

        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        self.added = {t["content"].encode(): t["id"] for t in spec.get("added_tokens", [])}
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        byte = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(shown))}
        ranks = {bytes(byte[c] for c in word): i for word, i in spec["model"]["vocab"].items() if all(c in byte for c in word)}
        ranks = {w: i for w, i in ranks.items() if w not in self.added}
        self.bpe = tiktoken.Encoding("words", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.width = np.zeros(max(ranks.values()) + 1, np.int64)
        for w, i in ranks.items():
            self.width[i] = len(w)
        self.keep = keep
        self._forget()

    def _forget(self) -> None:
        """The store: sorted hashes, with the place and length of each word's
        bytes and of its ids."""
        self.hashes, self.bytes, self.ids = np.zeros(0, np.uint64), np.zeros(0, np.uint8), np.zeros(0, np.uint32)
        self.word, self.at = np.zeros((0, 2), np.int64), np.zeros((0, 2), np.int64)

    def _added(self, data: np.ndarray, offsets: np.ndarray) -> list[tuple[int, int]]:
        """Places of added tokens within rows, leftmost first, the longest of
        those that start together."""
        found, raw = [], data.tobytes()
        for token in self.added:
            at = -1
            while (at := raw.find(token, at + 1)) >= 0:
                if offsets[np.searchsorted(offsets, at, "right")] >= at + len(token):
                    found.append((at, -len(token)))
        out, end = [], 0
        for at, size in sorted(found):
            if at >= end:
                out.append((at, end := at - size))
        return out

    def encode(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all rows, and the bounds of each row."""
        rows = len(offsets) - 1
        if not len(data):
            return np.zeros(0, np.uint32), np.zeros(rows + 1, np.int64)
        ends, starts = blanks(data)
        cut = np.zeros(len(data) + 1, bool)
        cut[1:-2] = (data[1:-1] == 32) & ~ends[:-2] & ~starts[2:]
        cut[offsets[1:-1] - 1] = False  # a space at the end of a row
        cut[offsets] = True
        for a, b in self._added(data, offsets):
            cut[a:b] = False
            cut[[a, b]] = True
        start = np.flatnonzero(cut[:-1])
        stop = np.append(start[1:], len(data))
        size = stop - start
        names, first, which = np.unique(span_hash(data, start, stop), return_index=True, return_inverse=True)
        bounds = np.searchsorted(start, offsets, "left")
        like = first[which]
        if not (np.array_equal(size, size[like]) and np.array_equal(data, data[ragged(start[like], size)])):
            return self._plainly(data, start, stop, bounds)
        a, n = start[first], size[first]
        spot = np.searchsorted(self.hashes, names)
        known = self.hashes[np.minimum(spot, len(self.hashes) - 1)] == names if len(self.hashes) else np.zeros(len(names), bool)
        if known.any():
            kept = self.word[spot[known]]
            if not np.array_equal(kept[:, 1], n[known]) or not np.array_equal(self.bytes[ragged(kept[:, 0], n[known])], data[ragged(a[known], n[known])]):
                self._forget()
                spot, known = np.zeros_like(spot), np.zeros_like(known)
        if not known.all():
            self._learn(names[~known], spot[~known], data, a[~known], n[~known], starts)
            spot = np.searchsorted(self.hashes, names)
        at = self.at[spot][which]
        total = np.concatenate([[0], np.cumsum(at[:, 1])])
        return self.ids[ragged(at[:, 0], at[:, 1])], total[bounds]

    def _one(self, word: bytes) -> np.ndarray:
        return np.array([self.added[word]] if word in self.added else self.bpe.encode_ordinary(word.decode()), np.uint32)

    def _plainly(self, data: np.ndarray, start: np.ndarray, stop: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Without the store, where two words of a batch have one hash."""
        parts = [self._one(data[a:b].tobytes()) for a, b in zip(start, stop, strict=True)]
        total = np.concatenate([[0], np.cumsum([len(p) for p in parts])])
        return np.concatenate(parts), total[bounds]

    def _learn(self, names: np.ndarray, spot: np.ndarray, data: np.ndarray, start: np.ndarray, size: np.ndarray, blank: np.ndarray) -> None:
        # words of one space and a character that is none are encoded together
        spaced = (data[start] == 32) & (size > 1) & ~blank[np.minimum(start + 1, len(data) - 1)]
        if any(token[:1] == b" " for token in self.added):
            spaced[:] = False
        count, parts = np.zeros(len(names), np.int64), []
        together, alone = np.flatnonzero(spaced), np.flatnonzero(~spaced)
        if len(together):
            ids = np.array(self.bpe.encode_ordinary(data[ragged(start[together], size[together])].tobytes().decode()), np.uint32)
            bound = np.searchsorted(np.cumsum(self.width[ids]), np.cumsum(size[together]), "left") + 1
            count[together] = np.diff(bound, prepend=0)
            parts.append(ids)
        for i in alone:
            parts.append(self._one(data[start[i] : start[i] + size[i]].tobytes()))
            count[i] = len(parts[-1])
        order = np.concatenate([together, alone])
        at = np.zeros((len(names), 2), np.int64)
        at[order, 0], at[:, 1] = np.cumsum(count[order]) - count[order] + len(self.ids), count
        word = np.stack([np.cumsum(size) - size + len(self.bytes), size], 1)
        self.hashes = np.insert(self.hashes, spot, names)
        self.word, self.at = np.insert(self.word, spot, word, 0), np.insert(self.at, spot, at, 0)
        self.bytes = np.concatenate([self.bytes, data[ragged(start, size)]])
        self.ids = np.concatenate([self.ids, *parts])

    def trim(self) -> None:
        """Between batches: forget all words when the store has grown too large."""
        if len(self.hashes) > self.keep:
            self._forget()


def cut_pieces(docs: DataFrame, tokenizer: str, pattern: str, capacity: int = 2048, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, piece, start, length, ids_crc32): the ids of each text and an id 0
    after them, cut into full pieces from the end, so that piece 0 may be
    shorter. A null text counts as empty and is the id 0 alone."""
    kind = docs.schema[key].dataType.simpleString()

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = WordTokenizer(tokenizer, pattern)
        for batch, data, offsets in slices(batches, "text", 1_000_000):
            ids, bounds = tokens.encode(data, offsets)
            out: list[list] = [[], [], [], [], []]
            for i in range(len(batch)):
                own = np.append(ids[bounds[i] : bounds[i + 1]], 0).astype("<u4")
                edges = [0, *range(len(own) % capacity or capacity, len(own) + 1, capacity)]
                for k, (a, b) in enumerate(zip(edges[:-1], edges[1:], strict=True)):
                    for column, value in zip(out, (i, k, a, b - a, zlib.crc32(own[a:b].tobytes())), strict=True):
                        column.append(value)
            rows = batch.column(0).take(pa.array(out[0], pa.int64()))
            yield pa.RecordBatch.from_arrays([rows, pa.array(out[1], pa.int32()), *[pa.array(c, pa.int64()) for c in out[2:]]], ["key", "piece", "start", "length", "ids_crc32"])
            tokens.trim()

    return docs.select(F.col(key).alias("key"), F.coalesce(F.col(text), F.lit("")).alias("text")).mapInArrow(pieces, f"key {kind}, {PIECES}")


def best_fit(lengths: dict[int, int], tokens: int = 2048, documents: int = 2048, attention: int | None = None, rule: str = "norm") -> list[tuple[int, int, int, int, int]]:
    """Placements (length, first rank, count, first bin, offset): the pieces of a
    length with ranks first..first+count-1 go to as many bins in turn, at the
    same offset. ``rule``: "norm" or "dot"."""
    attention = tokens * tokens if attention is None else attention
    full = np.array([tokens, documents, attention], float)
    state: dict[tuple[int, int, int], list[tuple[int, int]]] = {}  # residuals -> runs of bins
    out, bins = [], 0
    for length in sorted(lengths, reverse=True):
        rank, left = 0, lengths[length]
        need = np.array([length, 1, length * length])
        if length > tokens or length * length > attention or documents < 1:
            raise ValueError(f"a piece of {length} tokens fits no bin")
        while left:
            fits = [s for s in state if s[0] >= length and s[1] >= 1 and s[2] >= need[2]]
            if fits:
                rest = (np.array(fits) - need) / full
                score = -(rest**2).sum(1) if rule == "norm" else -((np.array(fits) / full) * (need / full)).sum(1)
                best = fits[max(range(len(fits)), key=lambda i: (score[i], -fits[i][0], fits[i]))]
                first, many = state[best].pop()
                if not state[best]:
                    del state[best]
            else:
                best, first = (tokens, documents, attention), bins
                per = int(min(tokens // length, documents, attention // need[2]))
                many = -(-left // per)
                bins += many
            take = min(many, left)
            if take < many:
                state.setdefault(best, []).append((first + take, many - take))
            out.append((length, rank, take, first, tokens - best[0]))
            rank, left = rank + take, left - take
            after = tuple(int(v) for v in np.array(best) - need)
            if after[0] > 0 and after[1] > 0 and after[2] > 0:
                state.setdefault(after, []).append((first, take))
    return out


def pack(pieces: DataFrame, tokens: int = 2048, documents: int = 2048, attention: int | None = None, rule: str = "norm", most: int = 100_000, key: str = "key") -> DataFrame:
    """``pieces`` with (sequence_id, offset). Ids of sequences are any numbers.
    ``most``: about so many counts of ranked groups go to the driver, so a group
    is a hundred-thousandth of the pieces, and 1000 at least."""
    spark, folder = pieces.sparkSession, workspace(pieces.sparkSession)
    # rows that repeat differ in their place, which is written with them
    placed = materialize(pieces.withColumn("place", F.monotonically_increasing_id()), folder, "pieces")
    lengths = {r["length"]: r["n"] for r in placed.groupBy("length").agg(F.count("*").alias("n")).collect()}
    group = max(1000, sum(lengths.values()) // most) if most else 1
    table = pa.table({"length": pa.array(lengths.keys(), pa.int64()), "salts": pa.array([-(-n // group) for n in lengths.values()], pa.int64())})
    salted = placed.join(F.broadcast(spark.createDataFrame(table)), "length").withColumn("salt", F.pmod(F.xxhash64("place"), "salts").cast("int")).select(*pieces.columns, "salt")
    counts = sorted((r["length"], r["salt"], r["n"]) for r in salted.groupBy("length", "salt").agg(F.count("*").alias("n")).collect())
    codes = np.array([(length << 40) + salt for length, salt, _ in counts], np.int64)
    before, seen = np.zeros(len(counts), np.int64), dict.fromkeys(lengths, 0)
    for i, (length, _, n) in enumerate(counts):
        before[i] = seen[length]
        seen[length] += n
    runs = np.array(sorted(best_fit(lengths, tokens, documents, attention, rule)), np.int64).reshape(-1, 5)
    plan = spark.sparkContext.broadcast((codes, before, (runs[:, 0] << 44) + runs[:, 1], runs))

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes, before, code, runs = plan.value
        for batch in batches:
            length, salt, rank = (batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("length", "salt", "rank"))
            rank = rank + before[np.searchsorted(codes, (length << 40) + salt)]
            run = runs[np.searchsorted(code, (length << 44) + rank, "right") - 1]
            out = batch.drop_columns(["salt", "rank"])
            yield out.append_column("sequence_id", pa.array(run[:, 3] + rank - run[:, 1])).append_column("offset", pa.array(run[:, 4]))

    ranked = salted.withColumn("rank", F.row_number().over(Window.partitionBy("length", "salt").orderBy(key, "piece", "start")).cast("long") - 1)
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in pieces.schema.fields)
    return ranked.mapInArrow(assign, f"{schema}, sequence_id long, offset long")


def packing_query(docs: DataFrame, capacity: int = 2048, key: str = "doc_id") -> DataFrame:
    import public_tokenizers

    pieces = cut_pieces(docs, public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.PATTERN, capacity, key)
    return pack(pieces, capacity).withColumnRenamed("key", key)
