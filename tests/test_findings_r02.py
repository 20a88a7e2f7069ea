"""Findings of the second round."""

import time
from concurrent.futures import ThreadPoolExecutor

import duckdb
import pytest

from querymend import catalog as C
from querymend import experiments, metrics, registry
from querymend.execution import Runner, by_keys, fingerprint, interpreted, open_db, same_result, scan_of, witness, written_witness
from querymend.mend import MendConfig
from querymend.perturb import made_from, rewrites
from querymend.sqltree import parse
from querymend.taxonomy import active_slots

SF = "/root/testdata/sf0.001"

SMALL = C.Catalog({"orders": {"o_orderkey": "bigint", "o_orderstatus": "string"}, "customer": {"c_custkey": "bigint", "c_mktsegment": "string"}}, values={"o_orderstatus": ["F", "O", "P"], "c_mktsegment": ["BUILDING", "AUTO-1", "AUTO-2"]})


def test_links_of_a_long_text_compare_each_word_once(monkeypatch):
    text = "Customers of the BUILDING market segment place order key 7 and orders of status F building auto"
    best = {}
    for t, cols in SMALL.columns.items():  # the columns' links as name_link has them, phrase by phrase
        for c in cols:
            for _, p in C.phrases(text):
                score = C.name_link(C.stem(c), p)
                if score >= 0.4 and round(score, 3) > best.get((t, c), (0, ""))[0]:
                    best[t, c] = (round(score, 3), p)
    links = C.question_links(text, SMALL)
    assert {(t, c): (weight, p) for p, t, c, rel, weight in links if c and rel != "link_value"} == best != {}
    assert [x for x in links if x[3] == "link_value"] == [("BUILDING", "customer", "c_mktsegment", "link_value", 1.0), ("F", "orders", "o_orderstatus", "link_value", 1.0)]
    calls = []
    plain = C.piece_of
    monkeypatch.setattr(C, "piece_of", lambda *x: calls.append(x) or plain(*x))
    long = C.question_links(" ".join([text] * 200), C.Catalog(SMALL.columns, values=SMALL.values))
    assert [x[1:3] for x in long if x[3] != "link_value"] == [x[1:3] for x in links if x[3] != "link_value"]
    assert len(calls) < 2000 * len(text.split())


TEXTS = [f"SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey > {k} ORDER BY 1" for k in range(20)]
TEXTS += ["SELECT nothing FROM orders", "SELECT CAST('x' AS INT) AS v FROM orders", "WITH a AS (SELECT 1.5 AS v) SELECT v, v FROM a -- end", "SELECT CAST(NULL AS DOUBLE) AS v, NULL AS w FROM nation"]


def test_queries_that_share_a_job_have_the_fingerprints_of_single_ones(spark):
    db = interpreted(open_db(spark, SF))
    jobs = []
    runner = Runner(db, together=16)
    plain = runner.some
    runner.some = lambda queries: jobs.append(len(queries)) or plain(queries)
    known = runner.all(TEXTS)
    assert len(jobs) <= 8 < len(TEXTS) and known == Runner(db).all(TEXTS)
    assert [known[t] is None for t in TEXTS] == [False] * 20 + [True, True, False, False]
    assert all(known[t] == tuple(fingerprint(db.sql(t)).first()) for t in TEXTS if known[t])


def test_train_inputs_are_made_once_for_all_models(spark):
    at = experiments.Lab.__new__(experiments.Lab)
    at.spark, at.catalog, at.failures, at.kept = spark, SMALL, {}, {}
    q = experiments.train_questions()[0]
    at.kept["made"] = [type("Row", (), {"gold": q.gold, "sql": q.gold + " LIMIT 0", "types": [12], "source": "rule"})]
    first = at.training(MendConfig(), active_slots()).count()
    assert at.inputs(MendConfig()) is at.inputs(MendConfig(growth=True))
    assert at.training(MendConfig(), active_slots(True)).count() == first == len(experiments.train_questions()) + 1
    row = at.training(MendConfig(), active_slots()).where("labels = array(12)").first()
    case = experiments.Case(q.text, q.gold + " LIMIT 0", SMALL, "links", q.evidence)
    assert list(row.words) == experiments.input_words(case, experiments.findings(case), "ok") and row.weight == 500


def test_cents_of_large_sums_count(spark):
    db = open_db(spark, SF)
    for whole in ("37523391258", "2251403475513"):
        for cents in ("00", "56"):
            total = f"SELECT CAST({whole}.{cents} AS DOUBLE) AS v"
            assert not same_result(db, total, f"{total[:-5]} + 0.01D AS v") and same_result(db, total, total)
    assert same_result(db, "SELECT 37523391258 AS v", "SELECT 37523391258D AS v")


def by_sql(name: str, table: str, sf_dir: str = SF) -> list[tuple]:
    con = duckdb.connect()
    con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{sf_dir}/{table}.parquet'")
    return sorted(con.execute(registry.ORACLES[name]).fetchall())


def test_union_of_types_over_orders(spark):
    got = sorted(map(tuple, registry.d_union(spark, SF).collect()))
    assert got == by_sql("d_union", "orders") and ("0", 0) < got[0]
    assert sum(n for _, n in got) == spark.read.parquet(f"{SF}/orders.parquet").count() > 4


def test_phrases_of_all_turns(spark):
    got = sorted(map(tuple, registry.a_phrases(spark, SF).collect()))
    assert got == by_sql("a_phrases", "conversations") and len(got) > 1


def test_nodes_of_the_conditions_of_all_customers(spark):
    got = sorted(map(tuple, registry.a_align(spark, SF).collect()))
    assert got == by_sql("a_align", "customer") and sum(n for role, _, n in got if role == "op") == spark.read.parquet(f"{SF}/customer.parquet").count()


def test_not_in_below_or_is_joined_by_equality(spark):
    db = open_db(spark, SF)
    db.sql("SELECT * FROM VALUES (1), (2), (NULL) AS t(a)").createOrReplaceTempView("some_a")
    for values in ("SELECT 1 AS b", "SELECT NULLIF(a, 2) AS b FROM some_a", "SELECT 1 AS b WHERE 1 = 0"):
        text = f"SELECT a FROM some_a WHERE a = 1 OR a NOT IN ({values})"
        assert by_keys(text) != text
        assert sorted(map(str, db.sql(by_keys(text)).collect())) == sorted(map(str, db.sql(text).collect()))
    text = "SELECT COUNT(*) AS n FROM part JOIN lineitem ON p_partkey = l_partkey WHERE p_type = 'LARGE' OR p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R')"
    plan = lambda q: db.sql(q)._jdf.queryExecution().executedPlan().toString()
    runner = Runner(db)
    assert "NestedLoop" in plan(text) and "NestedLoop" not in plan(runner.quick(text))
    assert runner.one(text) == tuple(fingerprint(db.sql(text)).first())
    for same in ("SELECT COUNT(*) AS n FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem)", "SELECT 1 AS n FROM part WHERE p_size = 1 OR p_size NOT IN (1, 2)"):
        assert by_keys(same) == same


def test_witness_draws_parts_and_keeps_those_of_its_lines(spark):
    db, w = open_db(spark, SF), witness(spark, SF, 50)
    whole, own = (d.table("part").select("p_partkey") for d in (db, w))
    lines = w.table("lineitem")
    unused = lambda d: d.join(lines, d["p_partkey"] == lines["l_partkey"], "left_anti").count()
    assert lines.join(own, lines["l_partkey"] == own["p_partkey"], "left_anti").count() == 0
    assert own.distinct().count() == own.count() and unused(own) < unused(whole)


def test_trees_of_the_queries_on_parts(spark):
    got = sorted(map(tuple, registry.a_tree(spark, SF).collect()))
    assert got == by_sql("a_tree", "part") and sum(r[-1] for r in got if r[1] == 0) == spark.read.parquet(f"{SF}/part.parquet").count()


def test_ancestors_in_the_queries_on_orders(spark):
    got = sorted(map(tuple, registry.a_ancestors(spark, SF).collect()))
    assert got == by_sql("a_ancestors", "orders") and sum(r[1] for r in got) == spark.read.parquet(f"{SF}/orders.parquet").count()


def test_subtrees_of_the_queries_on_orders(spark):
    got = sorted(map(tuple, registry.a_subtree(spark, SF).collect()))
    assert got == by_sql("a_subtree", "orders") and sum(r[1] for r in got) == spark.read.parquet(f"{SF}/orders.parquet").count()


def test_votes_over_the_orders_of_all_customers(spark):
    got = sorted(map(tuple, registry.b_vote(spark, SF).collect()))
    assert got == by_sql("b_vote", "orders") and len(got) > 4


def test_leaks_between_splits_of_conversations(spark):
    assert sorted(map(tuple, experiments.exp_leaks(spark, SF).collect())) == by_sql("exp_leaks", "conversations") != []


def test_leaks_are_found(spark, tmp_path):
    text = " ".join("abcdefghij")
    rows = [(1, 0, "user", text.upper()), (5, 0, "user", text), (10, 0, "user", f"x {text[2:]}\ty"), (15, 0, "user", text[6:]), (20, 0, "other", text), (25, 1, "user", None)]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").coalesce(1).write.parquet(f"{tmp_path}/conversations.parquet")
    got = sorted(map(tuple, experiments.exp_leaks(spark, str(tmp_path)).collect()))
    assert got == [("other", 0, 0), ("user", 1, 2)]


def test_rates_in_percent_of_returned_lines(spark):
    got = sorted(map(tuple, registry.m_published(spark, SF).collect()))
    assert got == by_sql("m_published", "lineitem") and len(got) == 3


def test_published_rates_follow_from_published_counts(spark):
    rows = [("mend", *c) for c in ((True, True, 516), (True, False, 161), (False, True, 128), (False, False, 729))]
    each = spark.createDataFrame(rows, "method string, truth_wrong boolean, flagged boolean, n int").selectExpr("method", "truth_wrong", "flagged", "explode(sequence(1, n))")
    r = metrics.detection_report(each).first()
    assert [round(100 * x, 2) for x in (r.precision, r.recall, r.accuracy, r.f1)] == [80.12, 76.22, 81.16, 78.12]


def test_names_of_added_columns_do_not_tell_the_type(spark):
    cat = C.catalog_of(spark, SF)
    named = lambda sql: {i.value for i in parse(sql).find("item") if i.value}
    golds = {q.gold for q in experiments.train_questions()}
    added = [t for g in golds for slot, t in rewrites(g, cat) if slot == 6]
    assert added and set().union(*map(named, added)) <= set().union(*map(named, golds))


def test_no_pair_of_types_is_always_left_out(spark):
    cat = C.catalog_of(spark, SF)
    golds = {q.gold for q in experiments.train_questions() if q.template == "type_back"}
    made = made_from(spark.createDataFrame([(g,) for g in golds], "gold string"), cat)
    assert (1, 9) in {tuple(r.types) for r in made.where("size(types) = 2").collect()}
    assert made.groupBy("gold").count().where("count > 30").count() == 0


def test_tables_of_a_written_witness_are_single_files_in_memory(spark):
    small = written_witness(spark, SF, 100_000)
    assert all(small.catalog.isCached(t) and small.table(t).rdd.getNumPartitions() == 1 for t in ("orders", "lineitem", "part", "nation"))


def test_what_threads_ask_for_is_made_once():
    at, made = experiments.Lab.__new__(experiments.Lab), []
    at.kept = {}

    def make():
        time.sleep(0.2)
        made.append(1)
        return len(made)

    assert experiments.ahead(*[lambda: at.once("x", make)] * 4) == [1] * 4


#: Queries of one source: counts, sums, rows, numbers, nulls, no rows, failing ones.
SHARED = [
    "SELECT COUNT(*) AS n FROM orders", "SELECT COUNT(*) AS n FROM orders WHERE o_orderstatus = 'F'", "SELECT ROUND(SUM(o_totalprice), 2) AS v, MAX(o_orderkey) AS k FROM orders WHERE o_totalprice > 1000 OR o_custkey < 9", "SELECT AVG(o_totalprice) AS v FROM orders WHERE o_orderkey < 0",
    "SELECT o_totalprice AS v, o_orderstatus AS s FROM orders WHERE o_totalprice > 150000", "SELECT o_orderkey AS k FROM orders WHERE o_orderkey < 0", "SELECT o_orderdate AS d FROM orders", "SELECT COUNT(missing) AS n FROM orders", "SELECT COUNT(*) AS n FROM orders WHERE o_orderstatus > 5",
    "SELECT COUNT(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey WHERE c_acctbal < 0", "SELECT o_orderkey AS k FROM customer LEFT JOIN orders ON c_custkey = o_custkey WHERE o_totalprice > 1000 AND c_acctbal < 100", "SELECT MIN(o_totalprice) + 1 AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey",
]


def test_queries_of_one_source_share_its_scan(spark):
    db = open_db(spark, SF)
    runner, plain = Runner(db), Runner(db)
    good = [q for q in SHARED if "missing" not in q and "> 5" not in q]
    runner.all(good)
    assert {q: runner.known[q] for q in good} == {q: plain.one(q) for q in good} and None not in runner.known.values()
    assert runner.jobs == 2
    other = Runner(db)
    assert other.all(SHARED) == {q: plain.one(q) for q in SHARED}  # with failing ones


@pytest.mark.parametrize("sql", ["SELECT DISTINCT o_custkey FROM orders", "SELECT COUNT(DISTINCT o_custkey) AS n FROM orders", "SELECT o_custkey AS k, COUNT(*) AS n FROM orders", "SELECT o_custkey FROM orders ORDER BY o_custkey LIMIT 3", "SELECT COUNT(*) AS n FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer)", "SELECT * FROM orders", "SELECT o_custkey AS k FROM orders GROUP BY o_custkey"])
def test_other_queries_have_their_own_scan(sql):
    assert scan_of(sql) is None


def test_a_text_that_a_thread_has_begun_is_run_once(spark):
    runner = Runner(open_db(spark, SF))
    with ThreadPoolExecutor(4) as pool:
        list(pool.map(lambda _: runner.all(SHARED), range(4)))
    assert runner.runs == len(SHARED) and not runner.begun
