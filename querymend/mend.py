"""Detection and repair of queries as one narrow pass over a table of
candidates: ``mapInPandas`` with the catalog, the model and the examples of the
train split broadcast, none of which grows with the data.

Detection joins what the static rules prove with what the model predicts.
Repair happens only where something was detected: every type is localised, its
context is cut out (smallest subtree, near schema, filled guideline, examples),
contexts are ordered by priority, and one rewrite uses them all."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .catalog import Catalog, linear_structure
from .detector import ErrorTokenModel, Segments, input_words
from .diagnose import Case, Finding, findings
from .sqltree import linearize, minimal_subtree, render
from .taxonomy import BY_SLOT, PRIORITY, SCOPE

CONTEXT = "struct<priority:int,slot:int,subtree:string,schema:string,guideline:string,examples:array<string>>"
OUT = f"question_id string, candidate_id string, question string, sql string, rule_types array<int>, model_types array<int>, types array<int>, is_wrong boolean, contexts array<{CONTEXT}>, refined_sql string"


@dataclass(frozen=True)
class MendConfig:
    """One switch for each ablation. ``edits``: most contexts that the refiner
    can serve in its one rewrite (a weaker refiner serves fewer)."""

    qss: bool = True
    ast: bool = True
    linking: str = "links"
    static: bool = True
    semantic: bool = True
    constrained: bool = True
    semantic_init: bool = True
    rule_data: bool = True
    assistant_data: bool = True
    localization: bool = True
    guidelines: bool = True
    sub_structures: bool = True
    few_shot: bool = True
    priority: bool = True
    growth: bool = False
    edits: int = 12


@dataclass
class Example:
    """A train query with a known error: its pooled input, types, and the reason
    of the finding whose edit gave the right rows."""

    slot: int
    reason: str
    text: str
    x: np.ndarray


def nearest(examples: list[Example], slot: int, x: np.ndarray, k: int = 3) -> list[Example]:
    """The k examples of a type whose inputs are nearest by cosine."""
    own = [e for e in examples if e.slot == slot]
    if not own:
        return []
    score = np.array([e.x for e in own]) @ x
    return [own[i] for i in sorted(range(len(own)), key=lambda i: (-score[i], own[i].text))[:k]]


@dataclass
class Context:
    """What the refiner gets for one type."""

    slot: int
    subtree: str
    schema: str
    guideline: str
    examples: list[Example]
    found: list[Finding]

    def row(self) -> dict:
        return {"priority": PRIORITY[self.slot], "slot": self.slot, "subtree": self.subtree, "schema": self.schema, "guideline": self.guideline, "examples": [e.text for e in self.examples]}


def extract(case: Case, slot: int, found: list[Finding], cfg: MendConfig, examples: list[Example], x: np.ndarray | None) -> Context:
    """The context of one type: its scope decides the subtree and how much of
    the schema goes along."""
    clause, reach = SCOPE[slot]
    own = [f for f in found if f.slot == slot]
    subtree, schema = linearize(case.tree), linear_structure(case.catalog, case.catalog.columns, case.links)
    if cfg.sub_structures and case.block is not None:
        part = case.block.kid(clause) if clause != "nodes" else minimal_subtree(case.tree, [n for f in own for n in f.nodes]) if own else None
        subtree = render(part) if part is not None else subtree
        names = {e.split(".")[0] for f in own for e in f.elements} | set(case.read)
        tables = [t for t in names if t in case.catalog.columns]
        schema = linear_structure(case.catalog, tables, [k for k in case.links if k[1] in tables]) if reach == "table" else ", ".join(sorted({e for f in own for e in f.elements}))
    texts = []
    for f in own or [None]:
        text = BY_SLOT[slot].guideline
        for k, v in (f.slots if f and cfg.guidelines else {}).items():
            text = text.replace("{" + k + "}", v)
        texts.append(text if cfg.guidelines else "")
    shown = nearest(examples, slot, x) if cfg.few_shot and x is not None else []
    return Context(slot, subtree, schema, "; ".join(dict.fromkeys(texts)), shown, own)


def _unguided(case: Case, f: Finding) -> None:
    """An edit whose guideline is not filled: the refiner knows the place and
    the kind, and takes the first thing that fits it."""
    n = f.nodes[0]
    if f.slot == 8 and n.role == "op":
        known = case.catalog.values.get(n.kids[0].value.split(".")[-1].lower())
        n.kids[1].value = f"'{known[0]}'" if known else n.kids[1].value
    elif f.slot == 11 and n.role == "func":
        n.value = "SUM" if n.value.upper() != "SUM" else "AVG"
    else:
        f.fix()


def rewrite(case: Case, contexts: list[Context], cfg: MendConfig) -> str:
    """One rewrite from all contexts, in their order. Of several findings of a
    type those are edited whose reason the examples show; without examples that
    agree, all. A context without its own subtree and schema cannot tell a way
    through other tables, and without localisation only the first place in the
    text is edited."""
    todo: list[Finding] = []
    for c in contexts[: cfg.edits]:
        shown = {e.reason for e in c.examples}
        fit = [f for f in c.found if f.reason in shown] or c.found
        if not cfg.sub_structures and c.slot in (1, 2):
            fit = [f for f in fit if f.slots.get("edge") or c.slot == 2 and len(case.outer) == 2]
        todo += fit
    if not cfg.localization:
        todo = sorted(todo, key=lambda f: f.nodes[0].start)[:1]
    for f in todo:
        try:
            f.fix() if cfg.guidelines else _unguided(case, f)
        except (KeyError, IndexError, ValueError, AttributeError):
            continue  # an earlier edit took away what this one needs
    return render(case.tree)


def detect(cases: list[Case], found: list[list[Finding]], model: ErrorTokenModel | None, cfg: MendConfig, feedback: list[str]) -> tuple[list[list[int]], list[list[int]], np.ndarray | None]:
    """(rule types, model types, pooled inputs) of a batch."""
    rules = [sorted({f.slot for f in fs if f.proof}) if cfg.static else [] for fs in found]
    if model is None or not cfg.semantic:
        return rules, [[] for _ in cases], None
    parts = Segments(cfg.qss, cfg.ast, cfg.static)
    inputs = [input_words(c, fs, fb, parts) for c, fs, fb in zip(cases, found, feedback, strict=True)]
    return rules, model.predict(inputs, cfg.constrained), model.words.pool(inputs) / 3


def mend_batch(questions: list[str], queries: list[str], evidence: list[str], feedback: list[str], catalog: Catalog, model: ErrorTokenModel | None, cfg: MendConfig, examples: list[Example] = ()) -> list[dict]:
    linking = cfg.linking if cfg.qss else "none"
    cases = [Case(q, s, catalog, linking, e) for q, s, e in zip(questions, queries, evidence, strict=True)]
    found = [findings(c, cfg.growth) for c in cases]
    rules, model_types, x = detect(cases, found, model, cfg, feedback)
    out = []
    for i, (case, fs) in enumerate(zip(cases, found, strict=True)):
        types = sorted({*rules[i], *model_types[i]}) or [0]
        contexts, refined = [], queries[i]
        if types != [0]:
            contexts = [extract(case, s, fs, cfg, list(examples), x[i] if x is not None else None) for s in types]
            contexts.sort(key=lambda c: (PRIORITY[c.slot], c.slot) if cfg.priority else (-PRIORITY[c.slot], -c.slot))
            rows = [c.row() for c in contexts]
            refined = rewrite(case, contexts, cfg) if any(c.found for c in contexts) else queries[i]
        else:
            rows = []
        out.append({"rule_types": rules[i], "model_types": model_types[i] or [0], "types": types, "is_wrong": types != [0], "contexts": rows, "refined_sql": refined})
    return out


def mend_one(question: str, sql: str, catalog: Catalog, model: ErrorTokenModel | None, cfg: MendConfig | None = None, evidence: str = "", feedback: str = "ok", examples: list[Example] = ()) -> dict:
    return mend_batch([question], [sql], [evidence], [feedback], catalog, model, cfg or MendConfig(), examples)[0]


def mend(candidates: DataFrame, catalog: Catalog, model: ErrorTokenModel | None = None, cfg: MendConfig | None = None, examples: list[Example] = ()) -> DataFrame:
    """``candidates``: question_id, candidate_id, question, sql, and where there
    are any evidence and feedback ("ok" or an error class). Null texts count as
    empty, and an empty query as one that does not parse."""
    cfg = cfg or MendConfig()
    shared = candidates.sparkSession.sparkContext.broadcast((catalog, model, list(examples)))
    more = [F.col(c) if c in candidates.columns else F.lit(d).alias(c) for c, d in (("evidence", ""), ("feedback", "ok"))]
    ids = ["question_id", "candidate_id", "question", "sql"]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        cat, net, shown = shared.value
        for frame in frames:
            for lo in range(0, len(frame), 500):
                part = frame.iloc[lo : lo + 500].reset_index(drop=True)
                text = {c: part[c].fillna("").tolist() for c in ("question", "sql", "evidence")}
                rows = mend_batch(text["question"], text["sql"], text["evidence"], part["feedback"].fillna("ok").tolist(), cat, net, cfg, shown)
                yield pd.concat([part[ids], pd.DataFrame(rows, columns=["rule_types", "model_types", "types", "is_wrong", "contexts", "refined_sql"])], axis=1)

    return candidates.select(*ids, *more).mapInPandas(run, OUT)


def rule_hits(candidates: DataFrame, catalog: Catalog) -> DataFrame:
    """(candidate_id, slot, proof, reason) of every finding."""
    shared = candidates.sparkSession.sparkContext.broadcast(catalog)

    def run(frames):
        for frame in frames:
            rows = [(i, f.slot, f.proof, f.reason) for i, q, s in zip(frame["candidate_id"], frame["question"], frame["sql"], strict=True) for f in findings(Case(q or "", s or "", shared.value))]
            yield pd.DataFrame(rows, columns=["candidate_id", "slot", "proof", "reason"])

    return candidates.select("candidate_id", "question", "sql").mapInPandas(run, "candidate_id string, slot int, proof boolean, reason string")


def union_types(df: DataFrame, rules: str = "rule_types", model: str = "model_types") -> DataFrame:
    """The union with null fallback as array functions."""
    both = F.array_except(F.array_union(rules, model), F.array(F.lit(0)))
    return df.withColumn("types", F.when(F.size(both) == 0, F.array(F.lit(0))).otherwise(F.array_sort(both)))


def taken(mended: DataFrame, runs: DataFrame) -> DataFrame:
    """A refined query that does not run is not taken: the first one stays.
    ``runs`` is (sql, runs) from the execution of the distinct texts."""
    known = runs.select(F.col("sql").alias("refined_sql"), "runs")
    kept = F.when(F.coalesce(F.col("runs"), F.lit(False)), F.col("refined_sql")).otherwise(F.col("sql"))
    return mended.join(known, "refined_sql", "left").withColumn("refined_sql", kept).drop("runs")


def without(flag: str) -> MendConfig:
    """The configuration of one ablation."""
    if flag == "linking":
        return MendConfig(linking="full")
    return replace(MendConfig(), **{flag: False})
