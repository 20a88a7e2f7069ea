"""Baselines as deterministic stand-ins for the published control structures:
what each can see, how often it touches a query, how it chooses.

Those that read one query work where the candidates lie; each returns a row
(flagged, proposals), its proposals best first. Those that vote are aggregates over the samples' results. No
stand-in sees the gold query or the model."""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bank import draw
from .catalog import Catalog
from .diagnose import Case, Finding, findings, observations
from .perturb import column_of, rewrites
from .sqltree import render
from .taxonomy import PRIORITY

PROPOSED = "candidate_id string, flagged boolean, proposals array<string>, types array<int>"


@dataclass
class Seen:
    """One candidate as a baseline sees it."""

    question: str
    sql: str
    evidence: str
    feedback: str
    catalog: Catalog

    def case(self) -> Case:
        return Case(self.question, self.sql, self.catalog, "links", self.evidence)

    def edit(self, pick: Callable[[Finding], bool], sql: str | None = None) -> str:
        case = Case(self.question, sql or self.sql, self.catalog, "links", self.evidence)
        for f in sorted((f for f in findings(case) if pick(f)), key=lambda f: (PRIORITY[f.slot], f.slot)):
            try:
                f.fix()
            except (KeyError, IndexError, ValueError, AttributeError):
                continue
        return render(case.tree)


def coverage(case: Case) -> float:
    """Share of the question's linked columns, tables and values that the query
    uses: all that a reader of names alone sees."""
    used = {column_of(n) for n in case.tree.find("column")}
    literals = {n.value.strip("'") for n in case.tree.find("literal")}
    hits = [c in used for _, _, c, _ in case.wanted] + [t in case.read for t in case.asked] + [v in literals for v, _, _ in case.asked_values()]
    return sum(hits) / len(hits) if hits else 1.0


def self_correction(s: Seen, gentle: bool) -> tuple[bool, list[str], list[int]]:
    """Reads question and query once. The plain prompt claims an error, and
    without one in sight the reader complies and changes something; the gentle
    one lets a query stand. The reader sees names, not the structure."""
    case = s.case()
    soft = [f for f in findings(case) if not f.proof and f.slot in (5, 6, 7, 8, 11)]
    if soft:
        new = s.edit(lambda f: (f.slot, f.reason) == (soft[0].slot, soft[0].reason))
        return new != s.sql, [new], [soft[0].slot]
    if not gentle or coverage(case) < 1 and draw("gentle", s.question, s.sql) < 0.5:
        other = [t for slot, t in rewrites(s.sql, s.catalog) if slot in (2, 6, 9)]
        if other:
            return True, other[:1], []
    return False, [], []


def self_debugging(s: Seen, rounds: int = 3) -> tuple[bool, list[str], list[int]]:
    """Touches only queries that fail, with what the error message names; every
    further proposal is the next round's."""
    if s.feedback == "ok":
        return False, [], []
    out, now = [], s.sql
    for _ in range(rounds):
        first = next((f.slot for f in findings(Case(s.question, now, s.catalog, "links", s.evidence)) if f.proof), None)
        new = s.edit(lambda f, first=first: f.proof and f.slot == first, now)
        if new == now:
            break
        out.append(new)
        now = new
    return True, out, []


def execution_refiner(s: Seen) -> tuple[bool, list[str], list[int]]:
    """Detects as self-debugging does, repairs with everything in sight."""
    if s.feedback == "ok":
        return False, [], []
    return True, [s.edit(lambda f: True), s.edit(lambda f: f.proof)], []


def agent_fixer(s: Seen) -> tuple[bool, list[str], list[int]]:
    """A reviewer goes through the clauses and flags what the links do not
    cover; a fixer proposes one edit a finding, a tester takes the first that
    runs. Clauses that no name covers (order, connective, function) and numbers
    are out of its sight."""
    case = s.case()
    gaps = {w.split(":")[0] for w in observations(case)} & {"tab-", "tab+", "tab~", "col-", "col~", "val-", "val~", "col+"}
    plain = gaps - {"col+"} or (gaps and draw("reviewer", s.question, s.sql) < 0.35)
    if not plain and s.feedback == "ok":
        return False, [], []
    found = [f for f in findings(case) if f.slot in (1, 2, 3, 4, 5, 6, 7, 8, 9)]
    proposals = [s.edit(lambda f, g=g: f.reason == g.reason and f.slot == g.slot) for g in found[:3]]
    if not proposals:
        proposals = [t for slot, t in rewrites(s.sql, s.catalog) if slot in (6, 9)][:1]
    return True, proposals, [f.slot for f in found[:3]]


def guideline_corrector(s: Seen, guideline: list[int]) -> tuple[bool, list[str], list[int]]:
    """Edits by a guideline learned from failures of the train split: the types
    that explain most of them, in that order, each if its pattern is met."""
    new = s.edit(lambda f: f.slot in guideline[:7])
    return new != s.sql, [new], []


def step_corrector(s: Seen) -> tuple[bool, list[str], list[int]]:
    """Rebuilds the steps of the query: schema steps first (tables, joins,
    columns), then values and conditions, then the last clause; of each kind the
    first that does not fit."""
    now = s.sql
    for slots in ((1, 2, 3, 4), (5, 6, 7), (8, 9)):
        first = next((f for f in findings(Case(s.question, now, s.catalog, "links", s.evidence)) if f.slot in slots), None)
        if first:
            now = s.edit(lambda f, g=first: f.slot == g.slot and f.reason == g.reason, now)
    if now == s.sql:
        first = next((f for f in findings(s.case()) if f.slot in (10, 11, 12)), None)
        if first:
            now = s.edit(lambda f, g=first: f.slot == g.slot and f.reason == g.reason, now)
    return now != s.sql, [now], []


def self_detection(s: Seen) -> tuple[bool, list[str], list[int]]:
    """Asks whether the query looks right: words of the question that the text
    of the query does not show."""
    words = [w for w in s.case().words if len(w) > 4 and w.isalpha()]
    return sum(w[:4] not in s.sql.lower() for w in words) > 0.75 * len(words), [], []


#: Words by which a reader without the structure guesses a type.
KEYWORDS = {"average": 11, "total": 11, "largest": 11, "highest": 12, "lowest": 12, "most": 12, "list": 5, "show": 5, "open": 9, "filled": 9, "returned": 9, "segment": 8, "brand": 8, "region": 1, "per": 12, "or": 10, "above": 10, "below": 10, "name": 7}


def keyword_types(s: Seen) -> tuple[bool, list[str], list[int]]:
    """Typed detection from words of the question alone."""
    types = sorted({slot for word, slot in KEYWORDS.items() if word in s.case().words})
    return bool(types), [], types


READERS: dict[str, Callable[..., tuple[bool, list[str], list[int]]]] = {
    "self_correction": lambda s, _: self_correction(s, False),
    "self_debugging": lambda s, _: self_debugging(s),
    "gentle_self_correction": lambda s, _: self_correction(s, True),
    "execution_refiner": lambda s, _: execution_refiner(s),
    "agent_fixer": lambda s, _: agent_fixer(s),
    "guideline_corrector": guideline_corrector,
    "step_corrector": lambda s, _: step_corrector(s),
    "self_detection": lambda s, _: self_detection(s),
    "keyword_types": lambda s, _: keyword_types(s),
}
VOTERS = ["self_consistency", "cross_consistency", "multiple_prompt"]
METHODS = [*READERS, *VOTERS, "rules_only"]


def learned_guideline(failures: list[tuple[int, ...]]) -> list[int]:
    """Slots by how often they explain failures of the train split."""
    return [s for s, _ in sorted(Counter(s for types in failures for s in types).items(), key=lambda x: (-x[1], x[0]))]


def read(candidates: DataFrame, method: str, catalog: Catalog, guideline: list[int] = ()) -> DataFrame:
    """(candidate_id, flagged, proposals, types) of one reader, best proposal
    first. ``candidates``: candidate_id, question, sql, evidence, feedback."""
    shared = candidates.sparkSession.sparkContext.broadcast((catalog, list(guideline)))
    name = method

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        cat, rules = shared.value
        for frame in frames:
            rows = []
            for r in frame.itertuples():
                flagged, proposals, types = READERS[name](Seen(r.question or "", r.sql or "", r.evidence or "", r.feedback or "ok", cat), rules)
                rows.append((r.candidate_id, flagged, [p for p in proposals if p != r.sql], types))
            yield pd.DataFrame(rows, columns=["candidate_id", "flagged", "proposals", "types"])

    return candidates.select("candidate_id", "question", "sql", "evidence", "feedback").mapInPandas(run, PROPOSED)


def tested(read: DataFrame, candidates: DataFrame, results: DataFrame) -> DataFrame:
    """(candidate_id, flagged, types, refined_sql): the first proposal that
    runs; without one the query as it was. ``results``: (sql, fp)."""
    tries = read.select("candidate_id", F.posexplode("proposals").alias("turn", "sql")).join(results, "sql").where("fp is not null")
    best = tries.groupBy("candidate_id").agg(F.min_by("sql", "turn").alias("refined"))
    both = candidates.select("candidate_id", "sql").join(read.select("candidate_id", "flagged", "types"), "candidate_id").join(best, "candidate_id", "left")
    return both.select("candidate_id", "flagged", "types", F.coalesce("refined", "sql").alias("refined_sql"))


def voted(samples: DataFrame, results: DataFrame) -> DataFrame:
    """(question_id, refined_sql, share): the query whose result most samples
    share. Failing samples have no vote; of ties the lowest sample counts, and
    of all failing ones the first. ``samples``: question_id, sample, sql, weight."""
    rows = samples.join(results, "sql", "left")
    votes = rows.groupBy("question_id", "fp").agg(F.sum("weight").alias("votes"), F.min(F.struct("sample", "sql")).alias("first"))
    order = Window.partitionBy("question_id").orderBy(F.col("fp").isNull(), F.desc("votes"), "first.sample")
    best = votes.withColumn("rank", F.row_number().over(order)).withColumn("all", F.sum("votes").over(Window.partitionBy("question_id"))).where("rank = 1")
    return best.select("question_id", F.col("first.sql").alias("refined_sql"), F.round(F.col("votes") / F.col("all"), 6).alias("share"))


def prompt_view(question: str, sql: str, catalog: Catalog, view: int) -> float:
    """How much a prompt view trusts a sample: views show the schema in another
    order or cut to the linked tables, so each weighs a sample by how well the
    part that it shows covers the query."""
    case = Case(question, sql, catalog)
    tables = sorted(catalog.columns, key=lambda t: draw("view", view, t))
    shown = set(tables[: len(tables) - view % 3]) | set(case.asked)
    read = set(case.read)
    return round(0.5 + 0.5 * (len(read & shown) / len(read) if read else 0) * coverage(case), 6)


def weighed(samples: DataFrame, catalog: Catalog) -> DataFrame:
    """``samples`` (question_id, sample, question, sql) with the weight that
    sample's own prompt view gives it."""
    shared = samples.sparkSession.sparkContext.broadcast(catalog)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            f = f.copy()
            f["weight"] = [prompt_view(q, s, shared.value, int(k)) for q, s, k in zip(f["question"], f["sql"], f["sample"], strict=True)]
            yield f

    return samples.select("question_id", "sample", "question", "sql").mapInPandas(run, "question_id string, sample int, question string, sql string, weight double")
