"""The experiment workloads on the question bank, as tables: candidates, results
of distinct texts, predictions of every method, outcomes. The driver launches
each distinct query once (``spark.sql`` needs it); all else is joined, mapped and
aggregated in Spark. Candidates, models and outcomes of a folder are kept."""

from __future__ import annotations

import os
from collections import Counter
from concurrent.futures import ThreadPoolExecutor
from functools import lru_cache, reduce
from string import ascii_lowercase, ascii_uppercase
from threading import Lock

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines as B
from . import metrics
from .bank import G1, G2, NoisyBackbone, Question, dev_questions, shifted, train_questions
from .catalog import catalog_of
from .detector import ErrorTokenModel, Segments, Words, input_words, learn_words
from .diagnose import Case, findings
from .execution import TABLES, Runner, feedback, folder_bytes, interpreted, open_db
from .inject import accepted, annotate
from .mend import Example, MendConfig, mend, without
from .perturb import changed, made_from, rewrites
from .taxonomy import CATEGORY_OF, active_slots

ABLATIONS = ["qss", "ast", "linking", "static", "semantic", "constrained", "semantic_init", "rule_data", "assistant_data", "localization", "guidelines", "sub_structures", "few_shot", "priority"]
CANDIDATE = "question_id string, candidate_id string, level string, question string, evidence string, gold string, sql string, truth_types array<int>, feedback string"
#: Bytes up to which starting a query takes longer than its rows, and the queries
#: that share a job there. Results are the same.
LITTLE, TOGETHER = 4 << 20, 16
#: Rewrites of a gold that are run to find those that change its result.
TRIED = 4


def ahead(*jobs) -> list:
    """The results of jobs that do not wait for each other, run side by side: one
    that keeps the driver busy leaves the executors to the others."""
    with ThreadPoolExecutor(8) as pool:
        return [f.result() for f in [pool.submit(job) for job in jobs]]


class Lab:
    """Catalog, results, models and outcomes of one database folder. ``share``
    of the dev questions is asked (1 but in tests)."""

    guard = Lock()

    def __init__(self, spark: SparkSession, sf_dir: str, share: float = 1.0):
        self.spark, self.share = spark, share
        self.failures, self.kept = {}, {}
        self.catalog, self.db = ahead(lambda: catalog_of(spark, sf_dir), lambda: open_db(spark, sf_dir))
        little = sum(folder_bytes(spark, f"{sf_dir}/{t}.parquet") for t in TABLES[:9]) <= LITTLE
        self.db.conf.set("spark.sql.adaptive.enabled", "false") if int(self.db.conf.get("spark.sql.shuffle.partitions")) == 1 else None
        self.runner = Runner(interpreted(self.db), together=TOGETHER) if little else Runner(self.db)

    # ---- results

    def run(self, queries) -> dict:
        """Fingerprints of the texts on the whole database; what fails is
        remembered with its error class."""
        queries = set(queries)
        known = self.runner.all(queries)
        failed = sorted(q for q in queries if known[q] is None and q not in self.failures)
        with ThreadPoolExecutor(8) as pool:
            self.failures |= zip(failed, pool.map(lambda q: feedback(self.db, q)["error_class"] or "EXECUTION", failed), strict=True)
        return known

    def results(self, queries) -> DataFrame:
        """(sql, fp) of distinct texts; fp is null where one fails."""
        queries = sorted(set(queries))
        known = self.run(queries)
        rows = [(q, None if known[q] is None else "|".join(map(str, known[q]))) for q in queries]
        return self.spark.createDataFrame(rows, "sql string, fp string").persist()

    def once(self, key, make):
        """What ``make`` returns, made once, also if several threads ask for it."""
        with self.guard:
            lock = self.kept.setdefault(("lock", key), Lock())
        with lock:
            if key not in self.kept:
                self.kept[key] = make()
        return self.kept[key]

    # ---- candidates

    def bank(self, name: str) -> list[Question]:
        return dev_questions(name, self.share) if name in "ab" else shifted(name, self.share)

    def tried(self, backbone: NoisyBackbone, questions: list[Question]) -> dict:
        """Results of every gold and the first options of its generator; what
        others have run besides is left out, as it depends on who was first."""
        golds = sorted({q.gold for q in questions})
        texts = golds + [t for g in golds for t, _ in backbone.options(g, self.catalog)[:TRIED]]
        known = self.run(texts)
        if any(known[g] is None for g in golds):
            raise ValueError("a gold query fails")
        return {t: known[t] for t in texts}

    def answers(self, backbone: NoisyBackbone, bank: str, sample: int = 0) -> dict:
        def make():
            known = self.tried(backbone, self.bank(bank))
            return backbone.answers(self.bank(bank), "a" if bank == "a" else "b", self.catalog, known, sample)

        return self.once(("answers", backbone.name, bank, sample), make)

    def candidates(self, backbone: NoisyBackbone, bank: str) -> DataFrame:
        """One answer a question. A query that fails carries its error class."""

        def make():
            got = self.answers(backbone, bank)
            rows = [(q.question_id, q.question_id, q.level, q.text, q.evidence, q.gold, got[q.question_id][0], list(got[q.question_id][1]), self.failures.get(got[q.question_id][0], "ok")) for q in self.bank(bank)]
            return self.spark.createDataFrame(rows, CANDIDATE).repartition(8).persist()

        return self.once(("candidates", backbone.name, bank), make)

    # ---- training

    def made(self) -> list:
        """Rows (gold, sql, types, source) of the train split, verified by
        execution: "rule" ones that change their gold's result, "assistant" ones
        whose labels stand because the assistant's query returns gold's rows, and
        "right" ones that return gold's rows."""

        def make():
            golds = self.spark.createDataFrame([(g,) for g in sorted({q.gold for q in train_questions()})], "gold string")
            rows = made_from(golds, self.catalog).persist()
            results = self.results((x for r in rows.select("gold", "sql").collect() for x in r))
            wrong = changed(rows, results).persist()
            labelled = annotate(wrong.where("source = 'free'")).persist()
            refined = self.results((x for r in labelled.select("refined", "gold").collect() for x in r))
            free = accepted(labelled, refined).select("gold", "sql", "types", F.lit("assistant").alias("source"))
            # a join that keeps every row changes nothing: right as well
            same = rows.where("source = 'right' or types = array(2)").join(wrong.select("gold", "sql"), ["gold", "sql"], "left_anti")
            right = same.select("gold", "sql", F.array().cast("array<int>").alias("types"), F.lit("right").alias("source"))
            kept = wrong.where("source = 'rule'").select("gold", "sql", "types", "source").unionByName(free).unionByName(right)
            return sorted(kept.collect(), key=lambda r: (r.gold, r.source, r.types, r.sql))

        return self.once("made", make)

    def asked(self, rows: list) -> list[tuple[Question, str, list[int], str]]:
        """Train rows with a question: the wordings of a gold take turns."""
        golds: dict[str, list[Question]] = {}
        for q in train_questions():
            golds.setdefault(q.gold, []).append(q)
        return [(golds[r.gold][i % len(golds[r.gold])], r.sql, list(r.types), r.source) for i, r in enumerate(rows)]

    def wrong_of_train(self) -> list[tuple[Question, str, list[int], str]]:
        """(question, wrong query, types, source) of the train split."""
        return self.asked([r for r in self.made() if r.source != "right"])

    def right_of_train(self) -> list[tuple[Question, str, list[int]]]:
        """(question, right query, no types): golds and what returns their rows."""
        return [(q, q.gold, []) for q in train_questions()] + [x[:3] for x in self.asked([r for r in self.made() if r.source == "right" and r.sql != r.gold])]

    def training(self, cfg: MendConfig, slots: list[int]) -> DataFrame:
        """(name, words, labels, weight): right and wrong queries, each half of
        the weight, as the model is to say both. Of the wrong ones, rows of a rare
        type weigh more, by the root of how rare it is."""
        kept = [(q, t, types) for q, t, types, source in self.wrong_of_train() if set(types) <= set(slots) and (cfg.rule_data if source == "rule" else cfg.assistant_data)]
        right = self.right_of_train()
        rows = []
        often = Counter(s for _, _, types in kept for s in types)
        rare = lambda types: min((often[s] for s in types), default=1) ** -0.5
        for own in (kept, right):
            total = sum(rare(types) for *_, types in own)
            rows += [(f"{q.question_id}/{i}", q.text, q.evidence, t, types, 500 * rare(types) / total) for i, (q, t, types) in enumerate(own)]
        named = self.spark.createDataFrame(rows, "name string, question string, evidence string, sql string, labels array<int>, weight double")
        return named.join(self.inputs(cfg), ["question", "evidence", "sql"]).select("name", "words", "labels", "weight").repartition(8, "name")

    def inputs(self, cfg: MendConfig) -> DataFrame:
        """(question, evidence, sql, words): the model's input of every train row,
        right or wrong, made where the rows lie and kept for all models whose
        input has the same parts."""
        linking, parts = cfg.linking if cfg.qss else "none", Segments(cfg.qss, cfg.ast, cfg.static)

        def make():
            rows = sorted({(q.text, q.evidence, t, self.failures.get(t, "ok")) for q, t, *_ in [*self.wrong_of_train(), *self.right_of_train()]})
            shared = self.spark.sparkContext.broadcast(self.catalog)

            def run(frames):
                import pandas as pd

                for f in frames:
                    cases = [Case(q, t, shared.value, linking, e) for q, e, t in zip(f["question"], f["evidence"], f["sql"], strict=True)]
                    words = [input_words(c, findings(c), fb, parts) for c, fb in zip(cases, f["feedback"], strict=True)]
                    yield pd.DataFrame({"question": f["question"], "evidence": f["evidence"], "sql": f["sql"], "words": words})

            texts = self.spark.createDataFrame(rows, "question string, evidence string, sql string, feedback string").repartition(32)
            return texts.mapInPandas(run, "question string, evidence string, sql string, words array<string>").persist()

        return self.once(("inputs", linking, parts), make)

    def model(self, cfg: MendConfig | None = None) -> ErrorTokenModel:
        cfg = cfg or MendConfig()
        key = ("model", cfg.qss, cfg.ast, cfg.linking, cfg.static, cfg.semantic_init, cfg.rule_data, cfg.assistant_data)

        def make():
            # the base vocabulary is learned without labels, from all inputs
            words: Words = learn_words(self.training(cfg, active_slots(True)))
            rows = self.training(cfg, active_slots())
            return ErrorTokenModel(words, active_slots(), "semantic" if cfg.semantic_init else "random").fit(rows)

        base = self.once(key, make)
        if not cfg.growth:
            return base
        new = [s for s in active_slots(True) if s not in active_slots()]
        return self.once((*key, "grown"), lambda: base.grown(self.training(cfg, active_slots(True)), new))

    def examples(self) -> list[Example]:
        """Train queries of which the edit of one finding gives gold's rows."""

        def make():
            from .sqltree import render

            tries = []
            for q, t, types, _ in self.wrong_of_train():
                for k in range(len(types) == 1 and 2):
                    case = Case(q.text, t, self.catalog, "links", q.evidence)
                    own = [f for f in findings(case) if f.slot == types[0]]
                    if k < len(own):
                        try:
                            own[k].fix()
                        except (KeyError, IndexError, ValueError, AttributeError):
                            continue
                        tries.append((q, t, types[0], own[k].reason, render(case.tree)))
            known = self.run([x for q, _, _, _, new in tries for x in (new, q.gold)])
            good = [(q, t, s, reason, new) for q, t, s, reason, new in tries if known[new] is not None and known[new] == known[q.gold]]
            cases = [Case(q.text, t, self.catalog, "links", q.evidence) for q, t, *_ in good]
            x = self.model().words.pool([input_words(c, findings(c)) for c in cases]) / 3 if good else []
            return [Example(s, reason, f"{q.text} {t} -> {new}", v) for (q, t, s, reason, new), v in zip(good, x, strict=True)]

        return self.once("examples", make)

    def guideline(self) -> list[int]:
        return B.learned_guideline([tuple(types) for _, _, types, _ in self.wrong_of_train()])

    # ---- predictions and outcomes

    def mended(self, backbone: NoisyBackbone, bank: str, cfg: MendConfig) -> DataFrame:
        net, shown, own = ahead(lambda: self.model(cfg) if cfg.semantic else None, lambda: self.examples() if cfg.few_shot and cfg.semantic else [], lambda: self.candidates(backbone, bank))
        return mend(own, self.catalog, net, cfg, shown)

    def predicted(self, backbone: NoisyBackbone, method: str, bank: str, cfg: MendConfig | None) -> DataFrame:
        """(candidate_id, flagged, types, refined_sql) of one method."""
        if method in ("mend", "rules_only"):
            cfg = cfg or MendConfig()
            got = self.mended(backbone, bank, cfg if method == "mend" else MendConfig(semantic=False, few_shot=False))
            return got.select("candidate_id", F.col("is_wrong").alias("flagged"), "types", "refined_sql")
        own = self.candidates(backbone, bank)
        same = F.array().cast("array<int>").alias("types")
        if method == "none":
            return own.select("candidate_id", F.lit(False).alias("flagged"), same, F.col("sql").alias("refined_sql"))
        if method in B.VOTERS:
            return self.votes(backbone, method, bank)
        got = B.read(own, method, self.catalog, self.guideline() if method == "guideline_corrector" else []).persist()
        texts = [r[0] for r in got.select(F.explode("proposals")).distinct().collect()]
        return B.tested(got, own, self.results(texts))

    def votes(self, backbone: NoisyBackbone, method: str, bank: str) -> DataFrame:
        other = G2 if backbone is G1 else G1
        drawn = {"self_consistency": [(backbone, k) for k in range(5)], "cross_consistency": [(backbone, 0), (backbone, 1), (other, 0)], "multiple_prompt": [(backbone, k) for k in range(4)]}[method]
        rows = [(q.question_id, i, q.text, self.answers(g, bank, k)[q.question_id][0]) for i, (g, k) in enumerate(drawn) for q in self.bank(bank)]
        samples = self.spark.createDataFrame(rows, "question_id string, sample int, question string, sql string")
        samples = B.weighed(samples, self.catalog) if method == "multiple_prompt" else samples.withColumn("weight", F.lit(1.0))
        got = B.voted(samples, self.results(r[3] for r in rows))
        own = self.candidates(backbone, bank).select("question_id", "candidate_id", "sql")
        return own.join(got, "question_id").select("candidate_id", (F.col("refined_sql") != F.col("sql")).alias("flagged"), F.array().cast("array<int>").alias("types"), "refined_sql")

    def outcomes(self, backbone: NoisyBackbone, method: str, bank: str = "a", cfg: MendConfig | None = None) -> DataFrame:
        """One row a question: was it wrong, flagged, mended, changed."""

        def make():
            made = self.predicted(backbone, method, bank, cfg).persist()
            own = self.candidates(backbone, bank)
            texts = {r[0] for r in made.select("refined_sql").distinct().collect()} | {x for r in own.select("gold", "sql").distinct().collect() for x in r}
            results = self.results(texts)
            fp = lambda name: results.select(F.col("sql").alias(name), F.col("fp").alias(f"{name}_fp"))
            rows = own.join(made, "candidate_id").join(fp("gold"), "gold").join(fp("sql"), "sql").join(fp("refined_sql"), "refined_sql")
            rows = rows.select(
                F.lit(backbone.name).alias("backbone"), F.lit(method).alias("method"), F.lit(bank).alias("bank"), "question_id", "level", (~F.col("sql_fp").eqNullSafe(F.col("gold_fp"))).alias("truth_wrong"), F.col("sql_fp").isNull().alias("failed"), "flagged",
                F.col("refined_sql_fp").eqNullSafe(F.col("gold_fp")).alias("refined_equals_gold"), (~F.col("refined_sql_fp").eqNullSafe(F.col("sql_fp"))).alias("changed_result"), F.col("refined_sql_fp").eqNullSafe(F.col("gold_fp")).alias("ex"), "truth_types", "types",
            )
            rows = rows.persist()
            rows.count()
            results.unpersist()
            made.unpersist()
            return rows

        return self.once(("outcomes", backbone.name, method, bank, cfg), make)

    def all(self, backbones, methods, bank: str = "a") -> DataFrame:
        return reduce(DataFrame.unionAll, self.each([(g, m, bank) for g in backbones for m in methods]))

    def each(self, asked: list[tuple]) -> list[DataFrame]:
        """The outcomes that are asked for, in their order. Those that need the
        model are begun first: it is made while other queries run."""
        order = sorted(range(len(asked)), key=lambda i: asked[i][1] not in ("mend", "guideline_corrector"))
        made = dict(zip(order, ahead(*[lambda a=asked[i]: self.outcomes(*a) for i in order]), strict=True))
        return [made[i] for i in range(len(asked))]


@lru_cache(4)
def _lab(spark: SparkSession, sf_dir: str, share: float) -> Lab:
    return Lab(spark, sf_dir, share)


def lab(spark: SparkSession, sf_dir: str) -> Lab:
    """The folder's lab. Its database is a session of its own, so that views of
    another folder cannot get in. QUERYMEND_SHARE asks a part of the questions."""
    return _lab(spark, sf_dir, float(os.environ.get("QUERYMEND_SHARE", "1")))


#: The methods of the main table, by generator.
TABLE = {"G1": ["none", "self_correction", "self_debugging", "self_consistency", "cross_consistency", "multiple_prompt", "gentle_self_correction", "execution_refiner", "agent_fixer", "guideline_corrector", "step_corrector"], "G2": ["none", "gentle_self_correction", "agent_fixer", "step_corrector"]}
WEAK = MendConfig(edits=1)


def _refine(spark: SparkSession, sf_dir: str, bank: str) -> DataFrame:
    at = lab(spark, sf_dir)
    asked = [(g, m, bank, None, m) for g in (G1, G2) for m in TABLE[g.name]] + [(g, "mend", bank, cfg, name) for g in (G1, G2) for name, cfg in (("mend_r1", WEAK), ("mend_r2", MendConfig()))]
    rows = [own.withColumn("method", F.lit(a[4])) for a, own in zip(asked, at.each([a[:4] for a in asked]), strict=True)]
    table = metrics.execution_accuracy(reduce(DataFrame.unionAll, rows), by=("backbone", "method"))
    plain = table.where("method = 'none'").select("backbone", "level", F.col("ex").alias("before"))
    joined = table.join(plain, (table["backbone"] == plain["backbone"]) & table["level"].eqNullSafe(plain["level"])).drop(plain["backbone"], plain["level"])
    return joined.select("backbone", "method", "level", "questions", "ex", metrics.ratio(F.col("ex") - F.col("before"), F.col("before")).alias("relative_gain"))


def exp_refine_a(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Execution accuracy by three levels: both generators, all methods."""
    return _refine(spark, sf_dir, "a")


def exp_refine_b(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same on the second bank, by four levels."""
    return _refine(spark, sf_dir, "b")


def exp_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = lab(spark, sf_dir)
    rows = reduce(DataFrame.unionAll, at.each([(G1, m, kind) for kind in ("b", "realistic", "synonym", "domain") for m in ("none", "agent_fixer", "mend")]))
    table = rows.groupBy(F.col("bank").alias("variant"), "method").agg(F.count("*").alias("questions"), metrics.ratio(metrics.n(F.col("ex")), F.count("*")).alias("ex"))
    plain = table.where("method = 'none'").select("variant", F.col("ex").alias("before"))
    return table.join(plain, "variant").select("variant", "method", "questions", "ex", F.round(100 * (F.col("ex") - F.col("before")), 4).alias("gain_points"))


def exp_detect(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = lab(spark, sf_dir)
    return metrics.detection_report(at.all([G1], ["self_detection", "gentle_self_correction", "execution_refiner", "agent_fixer", "rules_only", "mend"]))


def exp_depth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """True positives and the share of them that is fixed; one more row is plain
    self-correction given the method's true positives."""
    at = lab(spark, sf_dir)
    rows = at.all([G1], methods := ["self_debugging", "execution_refiner", "gentle_self_correction", "agent_fixer", "mend", "self_correction"]).where(F.col("method").isin(methods[:5]))
    hit = at.outcomes(G1, "mend").where("truth_wrong and flagged").select("question_id")
    same = at.outcomes(G1, "self_correction").join(hit, "question_id", "left_semi").withColumn("flagged", F.lit(True)).withColumn("method", F.lit("self_correction_equal_tp"))
    return metrics.fixed_rate(rows.unionByName(same))


def exp_decompose(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = lab(spark, sf_dir)
    rows = at.all([G1], ["self_correction", "gentle_self_correction", "self_debugging", "execution_refiner", "agent_fixer", "guideline_corrector", "step_corrector", "rules_only", "mend"])
    rates = metrics.corruption_rate(rows).select("method", "fp", "corruption_rate").join(metrics.fixed_rate(rows).select("method", "tp", "fixed_rate"), "method")
    return metrics.decompose_gain(rows).join(rates, "method")


def typed_cases(at: Lab) -> DataFrame:
    """Dev queries with one known error type each: verified rewrites of all
    types, the reserved ones included, on questions of the first bank."""

    def make():
        golds = {}
        for q in at.bank("a"):
            golds.setdefault(q.gold, q)
        made = []
        for q in golds.values():
            seen: dict[int, int] = {}
            for s, t in rewrites(q.gold, at.catalog):
                if seen.get(s, 0) < 1:
                    seen[s] = 1
                    made.append((q, s, t))
        known = at.run([x for q, _, t in made for x in (q.gold, t)])
        rows = [(q.question_id, f"{q.question_id}/{s}", q.text, t, [s], at.failures.get(t, "ok")) for q, s, t in made if known[t] != known[q.gold]]
        return at.spark.createDataFrame(rows, "question_id string, candidate_id string, question string, sql string, truth_types array<int>, feedback string").withColumn("evidence", F.lit("")).repartition(8).persist()

    return at.once("typed", make)


def typed(at: Lab, growth: bool) -> DataFrame:
    cfg = MendConfig(growth=growth)
    own = typed_cases(at)
    got = mend(own, at.catalog, at.model(cfg), cfg).select("candidate_id", "types")
    return own.select("candidate_id", "truth_types").join(got, "candidate_id").withColumn("method", F.lit("mend_grown" if growth else "mend"))


def exp_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Typed accuracy by the nine categories: the method and a reader of words.
    The two reserved categories score 0 until their types are switched on."""
    at = lab(spark, sf_dir)
    ahead(lambda: at.model(), lambda: typed_cases(at))
    words = B.read(typed_cases(at), "keyword_types", at.catalog).select("candidate_id", "types")
    other = typed_cases(at).select("candidate_id", "truth_types").join(words, "candidate_id").withColumn("method", F.lit("keyword_types"))
    return metrics.category_accuracy(typed(at, False).unionByName(other), CATEGORY_OF)


def exp_growth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Typed accuracy by slot before and after two reserved types are added;
    only their tokens are learned."""
    at = lab(spark, sf_dir)
    ahead(lambda: at.model(MendConfig(growth=True)), lambda: typed_cases(at))
    return metrics.type_specific_accuracy(typed(at, False).unionByName(typed(at, True)), by=("method",))


def exp_ablate(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = lab(spark, sf_dir)
    cut = at.each([(G1, "mend"), *[(G1, "mend", "a", without(flag)) for flag in ABLATIONS]])
    rows = [own.withColumn("removed", F.lit(flag)) for flag, own in zip(["none", *ABLATIONS], cut, strict=True)]
    out = reduce(DataFrame.unionAll, rows)
    f1 = metrics.detection_report(out, ("removed",)).select("removed", "precision", "recall", "f1")
    return f1.join(out.groupBy("removed").agg(metrics.ratio(metrics.n(F.col("ex")), F.count("*")).alias("ex")), "removed")


def exp_corr(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Correlation of the drops in F1 and in execution accuracy, over the
    ablations that touch detection."""
    table = exp_ablate(spark, sf_dir)
    full = table.where("removed = 'none'").select(F.col("f1").alias("f1_full"), F.col("ex").alias("ex_full"))
    drops = table.where(F.col("removed").isin(ABLATIONS[:9])).join(F.broadcast(full)).select((F.col("f1_full") - F.col("f1")).alias("f1_drop"), (F.col("ex_full") - F.col("ex")).alias("ex_drop"))
    return metrics.drop_correlation(drops)


def exp_pilot(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = lab(spark, sf_dir)
    return metrics.explicit_failure_share(at.all([G1, G2], ["none"]), ("backbone",))


def exp_leaks(spark: SparkSession, sf_dir: str, size: int = 8) -> DataFrame:
    """What train and dev split of conversations share, by role: texts, and dev
    turns that hold a run of ``size`` words of a train turn. Every fifth conversation
    is dev. (``leaks`` does the same for the question bank.)"""
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet")
    rows = turns.select("conv_id", "turn", F.col("role").alias("bank"), F.translate(F.coalesce("text", F.lit("")), ascii_uppercase, ascii_lowercase).alias("text"), (F.pmod("conv_id", F.lit(5)) == 0).alias("dev"))
    words = F.regexp_extract_all("text", F.lit(r"([^\x20\x09-\x0D]+)"), F.lit(1))
    starts = F.when(F.size("w") >= size, F.sequence(F.lit(1), F.size("w") - size + 1))
    runs = rows.withColumn("w", words).withColumn("i", F.explode(starts)).select("conv_id", "turn", "bank", "dev", F.array_join(F.slice("w", F.col("i"), size), " ").alias("run"))
    held = runs.where("dev").join(runs.where("not dev").select("bank", "run"), ["bank", "run"], "left_semi").groupBy("bank").agg(F.count_distinct("conv_id", "turn").alias("word_runs"))
    same = rows.where("dev").join(rows.where("not dev").select("bank", "text"), ["bank", "text"], "left_semi").groupBy("bank").agg(F.count_distinct("text").alias("texts"))
    return rows.select("bank").distinct().join(same, "bank", "left").join(held, "bank", "left").select("bank", F.coalesce("texts", F.lit(0)).alias("texts"), F.coalesce("word_runs", F.lit(0)).alias("word_runs"))
