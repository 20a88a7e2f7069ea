"""The model stage: error types as tokens of a grown vocabulary.

Base words have frozen vectors, learned from which words come together in the
inputs (positive pointwise mutual information, leading singular vectors). The
vocabulary grows by a null token and ``RESERVED`` error tokens; a type's token
starts as the mean of its words' vectors. Trained are these tokens and a
low-rank correction of the frozen projection. Error tokens are predicted one at
a time, from the pooled input and the sum of the tokens so far; the null token
or a token that came before ends the sequence. Decoding is masked to error
tokens in use.

Training reads rows where they lie: every round broadcasts the parameters, a
partition returns the sum of its gradients, the driver adds those and steps. Where
all pooled inputs are a few MB, the driver takes the same sums of the same
partitions itself. The result does not depend on how the rows are dealt (up to
rounding)."""

from __future__ import annotations

import copy
import hashlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .diagnose import Case, Finding, observations, path_words
from .sqltree import linearize, render
from .taxonomy import NULL_WORDS, RESERVED, TYPES

WIDTH, RANK = 160, 8
#: Most base words that have a vector of their own (the most frequent ones).
VOCABULARY = 4000
#: Bytes of pooled inputs up to which the rounds of a fit run in the driver.
NEAR = 32 << 20
#: Observations that come from the links, and those that come from the tree.
FROM_LINKS = ("tab", "col", "val", "num", "join", "arity")
FROM_TREE = ("fn", "ord", "grp", "bool", "cmp", "in", "items", "cond")


@dataclass(frozen=True)
class Segments:
    """Which parts the input has; the ablations switch them off."""

    structure: bool = True  # question-schema structure
    tree: bool = True
    rules: bool = True


def input_words(case: Case, found: list[Finding], feedback: str = "ok", parts: Segments = Segments()) -> list[str]:
    """The linear input as words: question, structure, query, tree, feedback,
    and last what the static rules found."""
    out = ["<in>", *(f"q:{w}" for w in case.words)]
    seen, speak = observations(case), True
    for w in seen:
        if ":" in w or w[-1:] in "-+~=" or "=" in w:
            head = w.split(":")[0].rstrip("-+~=").split("=")[0]
            speak = parts.structure if head in FROM_LINKS else parts.tree if head in FROM_TREE else True
        if speak:
            out.append(w)
    sql = render(case.tree) if case.tree.role != "error" else case.tree.value
    out += [f"s:{w}" for w in sql.lower().replace("(", " ").replace(")", " ").replace(",", " ").split()]
    if parts.tree:
        out += path_words(case.tree)
    out.append(f"fb:{feedback}")
    if parts.rules:
        out += [f"rule:{f.slot}" for f in found if f.proof for _ in range(2)]
    return out


def input_text(case: Case, found: list[Finding], feedback: str = "ok") -> str:
    """The same as text, for a model that reads text: definitions, question,
    structure, query, tree, feedback, rules."""
    from .catalog import linear_structure

    lines = ["; ".join(f"{t.slot} {t.code}: {' '.join(t.words)}" for t in TYPES if t.active), case.question, linear_structure(case.catalog, case.read, case.links), render(case.tree), linearize(case.tree), feedback, ", ".join(f.reason for f in found if f.proof)]
    return "\n".join(lines)


@dataclass
class Words:
    """Frozen vectors of the base words, and each word's weight in a pool."""

    index: dict[str, int]
    vectors: np.ndarray
    weight: np.ndarray

    def mean(self, words: Iterable[str]) -> np.ndarray:
        rows = [self.vectors[self.index[w]] for w in words if w in self.index]
        return np.mean(rows, axis=0) if rows else np.zeros(self.vectors.shape[1])

    def pool(self, inputs: list[list[str]]) -> np.ndarray:
        """One vector of length 3 an input; words without a vector count nothing."""
        out = np.zeros((len(inputs), self.vectors.shape[1]))
        for i, words in enumerate(inputs):
            at = np.array([self.index[w] for w in words if w in self.index], int)
            if len(at):
                out[i] = self.weight[at] @ self.vectors[at]
        return 3 * out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9)


def learn_words(inputs: DataFrame, width: int = WIDTH, most: int = VOCABULARY) -> Words:
    """Vectors from the inputs (``words`` array). Counting is an aggregate; the
    driver gets the counts of at most ``most`` words and of their pairs."""
    rows = inputs.select(F.array_distinct("words").alias("w")).persist(StorageLevel.MEMORY_AND_DISK)
    total = rows.count()
    single = rows.select(F.explode("w").alias("word")).groupBy("word").agg(F.count("*").alias("n")).where("n > 1").orderBy(F.desc("n"), "word").limit(most).toPandas()
    index = {w: i for i, w in enumerate(single["word"])}
    known = inputs.sparkSession.sparkContext.broadcast(index)
    schema = "a int, b int"

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ends = [[], []]
            for words in batch.column(0).to_pylist():
                own = np.array(sorted(known.value[w] for w in words if w in known.value), np.int32)
                i, j = np.triu_indices(len(own), 1)
                ends[0].append(own[i])
                ends[1].append(own[j])
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(e) if e else np.zeros(0, np.int32)) for e in ends], ["a", "b"])

    both = rows.mapInArrow(pairs, schema).groupBy("a", "b").agg(F.count("*").alias("n")).toPandas()
    rows.unpersist()
    n = single["n"].to_numpy(float)
    table = np.zeros((len(n), len(n)))
    a, b = both["a"].to_numpy(), both["b"].to_numpy()
    table[a, b] = table[b, a] = np.maximum(0, np.log(both["n"].to_numpy() * total / (n[a] * n[b])))
    np.fill_diagonal(table, np.log(total / n) + 1)
    values, vectors = np.linalg.eigh(table)
    order = np.argsort(-values)[:width]
    made = vectors[:, order] * np.sqrt(np.maximum(values[order], 0))
    made = np.pad(made, ((0, 0), (0, width - made.shape[1])))
    sign = np.sign(made[np.abs(made).argmax(0), np.arange(width)])  # one of two equal bases
    return Words(index, made * np.where(sign == 0, 1, sign) / np.maximum(np.linalg.norm(made, axis=1, keepdims=True), 1e-9), np.log(total / n) + 0.05)


def masked(scores: np.ndarray, allowed: np.ndarray) -> np.ndarray:
    """Probabilities over the allowed columns, which sum to 1; 0 elsewhere."""
    top = np.where(allowed, scores, -np.inf)
    p = np.exp(top - top.max(-1, keepdims=True))
    return p / p.sum(-1, keepdims=True)


def serial(labels: list[int], name: str, turn: int) -> list[int]:
    """A label set in an order drawn from the row's name and the turn."""
    return sorted(labels, key=lambda s: hashlib.md5(f"{name}|{turn}|{s}".encode()).digest()) or [0]


@dataclass
class ErrorTokenModel:
    words: Words
    active: list[int]
    init: str = "semantic"
    seed: int = 0
    tokens: np.ndarray = field(init=False)

    def __post_init__(self):
        width = self.words.vectors.shape[1]
        rng = np.random.default_rng(self.seed)
        spare = rng.normal(size=(RESERVED + 1, width)) / np.sqrt(width)
        self.tokens = spare  # row 0: null; rows beyond the taxonomy stay in reserve
        if self.init == "semantic":
            self.tokens[0] = self.words.mean(NULL_WORDS)
            for t in TYPES:
                self.tokens[t.slot] = self.words.mean(t.words)
        self.project = np.linalg.qr(rng.normal(size=(width, width)))[0]
        self.low_a, self.low_b = rng.normal(size=(width, RANK)) * 0.1, np.zeros((RANK, width))

    @property
    def allowed(self) -> np.ndarray:
        out = np.zeros(RESERVED + 1, bool)
        out[[0, *self.active]] = True
        return out

    def hidden(self, x: np.ndarray, emitted: np.ndarray) -> np.ndarray:
        z = x + emitted @ self.tokens
        return z @ self.project + z @ self.low_a @ self.low_b

    def steps(self, labels: list[list[int]], names: list[str], turn: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(row, emitted, target, share) of all predictions of a turn. The shares
        of a row's tokens sum to 1; ending a sequence has a token's share more."""
        row, emitted, target, share = [], [], [], []
        for i, (slots, name) in enumerate(zip(labels, names, strict=True)):
            order = serial(slots, name, turn)
            done = np.zeros(RESERVED + 1)
            for k, s in enumerate([*order, 0] if order != [0] else order):
                row.append(i)
                emitted.append(done.copy())
                target.append(s)
                share.append(1 / len(order) if k < len(order) else 0.5 / len(order))
                done[s] += 1
        return np.array(row), np.array(emitted), np.array(target), np.array(share)

    def gradients(self, x: np.ndarray, labels: list[list[int]], names: list[str], weight: np.ndarray, turn: int) -> tuple[float, list[np.ndarray]]:
        """Sums over rows of the set loss and of its gradients by tokens and by
        the low-rank factors."""
        row, m, t, share = self.steps(labels, names, turn)
        z = x[row] + m @ self.tokens
        hid = z @ self.project + z @ self.low_a @ self.low_b
        p = masked(hid @ self.tokens.T, self.allowed)
        w = share * weight[row]
        loss = -float((w * np.log(p[np.arange(len(t)), t] + 1e-12)).sum())
        ds = p * w[:, None]
        ds[np.arange(len(t)), t] -= w
        dh = ds @ self.tokens
        dz = dh @ self.project.T + dh @ self.low_b.T @ self.low_a.T
        return loss, [ds.T @ hid + m.T @ dz, z.T @ (dh @ self.low_b.T), (z @ self.low_a).T @ dh]

    def set_loss(self, x: np.ndarray, labels: list[int], name: str = "", turn: int = 0) -> float:
        """The loss of one row without the step that ends its sequence: the mean
        over its set, in the order of the turn."""
        order = serial(labels, name, turn)
        done, total = np.zeros(RESERVED + 1), 0.0
        for s in order:
            p = masked(self.hidden(x[None], done[None]) @ self.tokens.T, self.allowed)[0]
            total -= float(np.log(p[s] + 1e-12))
            done[s] += 1
        return total / len(order)

    def fit(self, rows: DataFrame, rounds: int = 100, rate: float = 0.08, only: list[int] | None = None, decay: float = 1e-4) -> ErrorTokenModel:
        """``rows``: name, words, labels, weight. ``only``: learn these tokens
        and leave all else as it is (types that are added later)."""
        context = rows.sparkSession.sparkContext
        shared = context.broadcast(self.words)

        def pooled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                x = shared.value.pool(b.column(1).to_pylist())
                own = [b.column(0).to_pylist()], [x.tobytes()], [b.column(2).to_pylist()], [b.column(3).to_pylist()]
                kinds = pa.list_(pa.string()), pa.binary(), pa.list_(pa.list_(pa.int32())), pa.list_(pa.float64())
                yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(own, kinds, strict=True)], ["names", "x", "labels", "weights"])

        # a batch is one row; a round over an RDD needs no plan of its own
        pools = rows.select("name", "words", "labels", F.col("weight").cast("double")).mapInArrow(pooled, "names array<string>, x binary, labels array<array<int>>, weights array<double>")
        table = pools.coalesce(64).rdd.map(tuple).persist(StorageLevel.MEMORY_AND_DISK)
        total, size = table.map(lambda b: (sum(b[3]), len(b[1]))).fold((0.0, 0), lambda a, b: (a[0] + b[0], a[1] + b[1]))
        # a round of a small table takes less time than to start its tasks
        near = table.glom().collect() if size <= NEAR else None
        params = [self.tokens, self.low_a, self.low_b]
        moment = [[np.zeros_like(p), np.zeros_like(p)] for p in params]
        self.losses = []
        for turn in range(rounds if total else 0):
            light = copy.copy(self)  # gradients need no words, by far the largest part
            light.words = None

            def part(batches: Iterable[tuple], model: ErrorTokenModel, turn=turn) -> Iterator[tuple]:
                loss, sums = 0.0, None
                for names, x, labels, weights in batches:
                    if names:
                        one, grads = model.gradients(np.frombuffer(x).reshape(len(names), -1), labels, names, np.array(weights), turn)
                        loss, sums = loss + one, grads if sums is None else [s + g for s, g in zip(sums, grads, strict=True)]
                if sums is not None:
                    yield loss, *[g.tobytes() for g in sums]

            if near is not None:
                got = [r for batches in near for r in part(batches, light)]
            else:
                model = context.broadcast(light)
                got = table.mapPartitions(lambda batches, model=model, part=part: part(batches, model.value)).collect()
                model.unpersist()
            self.losses.append(sum(r[0] for r in got) / total)
            for k, p in enumerate(params):
                g = sum(np.frombuffer(r[k + 1]).reshape(p.shape) for r in got) / total + decay * p
                if only is not None:
                    g = np.where(np.isin(np.arange(len(p)), only)[:, None], g, 0) if k == 0 else np.zeros_like(p)
                m, v = moment[k]
                m += 0.1 * (g - m)
                v += 0.001 * (g * g - v)
                step = rate * min(1, 2 * (1 - turn / rounds)) * (m / (1 - 0.9 ** (turn + 1))) / (np.sqrt(v / (1 - 0.999 ** (turn + 1))) + 1e-8)
                p -= step if only is None or k == 0 else 0
        table.unpersist()
        return self

    def predict(self, inputs: list[list[str]], constrained: bool = True) -> list[list[int]]:
        """Error slots of each input; empty for the null token. Unconstrained,
        base words compete, and one that wins ends the sequence."""
        x = self.words.pool(inputs)
        emitted, live, out = np.zeros((len(x), RESERVED + 1)), np.arange(len(x)), [[] for _ in inputs]
        while len(live):
            h = self.hidden(x[live], emitted[live])
            scores = h @ self.tokens.T
            if constrained:
                best = masked(scores, self.allowed).argmax(1)
            else:
                best = np.concatenate([scores, h @ self.words.vectors.T], 1).argmax(1)
            go = (best > 0) & (best <= RESERVED)
            go &= emitted[live, np.minimum(best, RESERVED)] == 0
            go &= self.allowed[np.minimum(best, RESERVED)]
            live, best = live[go], best[go]
            emitted[live, best] += 1
            for i, s in zip(live.tolist(), best.tolist(), strict=True):
                out[i].append(s)
        return [sorted(s) for s in out]

    def grown(self, rows: DataFrame, slots: list[int], **options) -> ErrorTokenModel:
        """A copy with further types in use, whose tokens alone are learned.
        Their rows, few among all, get a third of the weight."""
        new = copy.deepcopy(self)
        new.active = sorted({*self.active, *slots})
        theirs = F.arrays_overlap("labels", F.array(*[F.lit(s) for s in slots]))
        sums = rows.groupBy(theirs.alias("own")).agg(F.sum("weight").alias("w")).collect()
        own, rest = (sum(r.w for r in sums if bool(r.own) is b) for b in (True, False))
        return new.fit(rows.withColumn("weight", F.when(theirs, F.col("weight") * (0.5 * rest / own if own else 1.0)).otherwise(F.col("weight"))), only=slots, **options)
