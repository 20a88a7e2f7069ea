"""Operator entries: a Spark plan and the DuckDB SQL it must agree with."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import metrics
from ..execution import TABLES
from ..taxonomy import CATEGORY_OF

Entry = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Entry] = {}
ORACLES: dict[str, str] = {}


def entry(sql: str | None):
    def keep(f: Entry) -> Entry:
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return keep


def t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


@entry("SELECT o_orderkey AS k FROM orders WHERE o_orderpriority IN ('1-URGENT','2-HIGH') AND o_totalprice BETWEEN 1000 AND 50000 AND o_orderstatus LIKE 'F%'")
def o_filter_compound(s, d):
    return t(s, d, "orders").where(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_totalprice").between(1000, 50000) & F.col("o_orderstatus").like("F%")).select(F.col("o_orderkey").alias("k"))


@entry("SELECT p_partkey AS k, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS c FROM part")
def o_project_case(s, d):
    return t(s, d, "part").select(F.col("p_partkey").alias("k"), F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large").alias("c"))


@entry("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def o_join_broadcast(s, d):
    """region is five rows by definition."""
    return t(s, d, "nation").join(F.broadcast(t(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")


@entry("SELECT o_orderpriority AS p, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def o_join_sortmerge(s, d):
    return t(s, d, "lineitem").select("l_orderkey").hint("merge").join(t(s, d, "orders").select("o_orderkey", "o_orderpriority"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy(F.col("o_orderpriority").alias("p")).agg(F.count("*").alias("n"))


@entry("SELECT c_mktsegment AS seg, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def o_join_shufflehash(s, d):
    return t(s, d, "orders").join(t(s, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy(F.col("c_mktsegment").alias("seg")).agg(F.count("*").alias("n"))


@entry("SELECT n_name, count(s_suppkey) AS n FROM nation LEFT JOIN (SELECT * FROM supplier WHERE s_acctbal > 5000) ON s_nationkey = n_nationkey GROUP BY 1")
def o_join_left(s, d):
    return t(s, d, "nation").join(t(s, d, "supplier").where("s_acctbal > 5000"), F.col("s_nationkey") == F.col("n_nationkey"), "left").groupBy("n_name").agg(F.count("s_suppkey").alias("n"))


@entry("SELECT coalesce(a.k, b.k) AS k, a.n AS x, b.n AS y FROM (SELECT s_nationkey AS k, count(*) AS n FROM supplier WHERE s_acctbal > 5000 GROUP BY 1) a FULL JOIN (SELECT c_nationkey AS k, count(*) AS n FROM customer WHERE c_acctbal > 9500 GROUP BY 1) b ON a.k = b.k")
def o_join_full(s, d):
    a = t(s, d, "supplier").where("s_acctbal > 5000").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("x"))
    b = t(s, d, "customer").where("c_acctbal > 9500").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("y"))
    return a.join(b, "k", "full")


@entry("SELECT c_custkey AS k FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def o_semi(s, d):
    return t(s, d, "customer").join(t(s, d, "orders").where("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select(F.col("c_custkey").alias("k"))


@entry("SELECT c_custkey AS k FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
def o_anti(s, d):
    return t(s, d, "customer").join(t(s, d, "orders").where("o_orderstatus = 'F'"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select(F.col("c_custkey").alias("k"))


@entry("SELECT p_partkey AS k FROM part WHERE p_partkey NOT IN (SELECT CASE WHEN l_quantity = 51 THEN NULL ELSE l_partkey END FROM lineitem WHERE l_quantity >= 49)")
def o_null_aware_not_in(s, d):
    t(s, d, "part").createOrReplaceTempView("part")
    t(s, d, "lineitem").createOrReplaceTempView("lineitem")
    return s.sql(ORACLES["o_null_aware_not_in"])


@entry("SELECT count(*) AS n FROM supplier JOIN region ON s_acctbal > 1000 * r_regionkey")
def o_theta(s, d):
    return t(s, d, "supplier").join(F.broadcast(t(s, d, "region")), F.col("s_acctbal") > 1000 * F.col("r_regionkey")).agg(F.count("*").alias("n"))


@entry("SELECT a.event_id AS s, b.event_id AS e FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 60 MINUTE WHERE a.event_type = 'signup' AND b.event_type = 'error'")
def o_range_bucket(s, d):
    """Range join as an equi join on hour buckets, each start in two of them."""
    e = t(s, d, "events").withColumn("h", F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / 3600))
    a = e.where("event_type = 'signup'").select("user_id", F.col("ts").alias("t0"), F.col("event_id").alias("s"), F.explode(F.array("h", F.col("h") + 1)).alias("h"))
    b = e.where("event_type = 'error'").select("user_id", "ts", F.col("event_id").alias("e"), "h")
    return a.join(b, ["user_id", "h"]).where("ts > t0 AND ts <= t0 + INTERVAL 60 MINUTES").select("s", "e")


@entry("SELECT p.event_id AS k, (SELECT c.event_id FROM events c WHERE c.user_id = p.user_id AND c.event_type = 'click' AND (c.ts < p.ts OR c.ts = p.ts AND c.event_id < p.event_id) ORDER BY c.ts DESC, c.event_id DESC LIMIT 1) AS click FROM events p WHERE p.event_type = 'purchase'")
def o_asof(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    e = t(s, d, "events").where("event_type IN ('click', 'purchase')")
    return e.withColumn("click", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), True).over(w)).where("event_type = 'purchase'").select(F.col("event_id").alias("k"), "click")


@entry("SELECT l_returnflag AS f, l_linestatus AS s, count(*) AS n, round(sum(l_quantity), 2) AS q, round(avg(l_discount), 6) AS d, min(l_tax) AS lo, max(l_tax) AS hi, round(stddev_samp(l_quantity), 4) AS sd FROM lineitem GROUP BY 1, 2")
def o_agg_multi(s, d):
    return t(s, d, "lineitem").groupBy(F.col("l_returnflag").alias("f"), F.col("l_linestatus").alias("s")).agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"), F.round(F.avg("l_discount"), 6).alias("d"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"), F.round(F.stddev("l_quantity"), 4).alias("sd"))


@entry("SELECT o_orderpriority AS p, count(DISTINCT o_custkey) AS c, count(*) FILTER (o_orderstatus = 'F') AS f FROM orders GROUP BY 1")
def o_agg_distinct(s, d):
    return t(s, d, "orders").groupBy(F.col("o_orderpriority").alias("p")).agg(F.count_distinct("o_custkey").alias("c"), F.count_if(F.col("o_orderstatus") == "F").alias("f"))


@entry("SELECT o_orderpriority AS p, count(DISTINCT o_custkey) AS n, true AS close FROM orders GROUP BY 1")
def o_agg_approx(s, d):
    """Exact counts, and whether the sketch is within 5 % of each."""
    exact = F.count_distinct("o_custkey")
    return t(s, d, "orders").groupBy(F.col("o_orderpriority").alias("p")).agg(exact.alias("n"), (F.abs(F.approx_count_distinct("o_custkey", 0.01) - exact) <= 0.05 * exact).alias("close"))


@entry("SELECT o_orderpriority AS p, round(quantile_cont(o_totalprice, 0.5), 4) AS m FROM orders GROUP BY 1")
def o_percentile(s, d):
    return t(s, d, "orders").groupBy(F.col("o_orderpriority").alias("p")).agg(F.round(F.percentile("o_totalprice", 0.5), 4).alias("m"))


@entry("SELECT r_name AS r, n_name AS n, count(*) AS c FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def o_rollup(s, d):
    return _geo(s, d).rollup(F.col("r_name").alias("r"), F.col("n_name").alias("n")).agg(F.count("*").alias("c"))


@entry("SELECT r_name AS r, c_mktsegment AS m, count(*) AS c FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (r_name, c_mktsegment)")
def o_cube(s, d):
    return _geo(s, d).cube(F.col("r_name").alias("r"), F.col("c_mktsegment").alias("m")).agg(F.count("*").alias("c"))


@entry("SELECT r_name AS r, c_mktsegment AS m, count(*) AS c FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY GROUPING SETS ((r_name), (c_mktsegment))")
def o_sets(s, d):
    return _geo(s, d).groupingSets([[F.col("r_name")], [F.col("c_mktsegment")]], "r_name", "c_mktsegment").agg(F.count("*").alias("c")).withColumnsRenamed({"r_name": "r", "c_mktsegment": "m"})


def _geo(s, d):
    return t(s, d, "customer").join(t(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))


@entry("SELECT CAST(year(o_orderdate) AS INT) AS y, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o FROM orders GROUP BY 1")
def o_pivot(s, d):
    return t(s, d, "orders").groupBy(F.year("o_orderdate").alias("y")).pivot("o_orderstatus", ["F", "O"]).agg(F.count("o_orderkey")).na.fill(0).withColumnsRenamed({"F": "f", "O": "o"})


@entry("SELECT r_regionkey AS k, 'a' AS name, r_regionkey * 2 AS v FROM region UNION ALL SELECT r_regionkey, 'b', r_regionkey * 3 FROM region")
def o_unpivot(s, d):
    return t(s, d, "region").select(F.col("r_regionkey").alias("k"), (F.col("r_regionkey") * 2).alias("a"), (F.col("r_regionkey") * 3).alias("b")).unpivot("k", ["a", "b"], "name", "v")


@entry("SELECT o_orderkey AS k, row_number() OVER w AS rn, rank() OVER w AS r, dense_rank() OVER w AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)")
def o_win_rank(s, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t(s, d, "orders").select(F.col("o_orderkey").alias("k"), F.row_number().over(w).alias("rn"), F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"))


@entry("SELECT o_orderkey AS k, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS v FROM orders")
def o_win_frame(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)
    return t(s, d, "orders").select(F.col("o_orderkey").alias("k"), F.round(F.sum("o_totalprice").over(w), 2).alias("v"))


@entry("SELECT o_orderkey AS k, lag(o_orderkey) OVER w AS a, lead(o_orderkey) OVER w AS b FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def o_win_lag(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return t(s, d, "orders").select(F.col("o_orderkey").alias("k"), F.lag("o_orderkey").over(w).alias("a"), F.lead("o_orderkey").over(w).alias("b"))


@entry("SELECT p_partkey AS k, p_retailprice AS v FROM part ORDER BY v DESC, k LIMIT 10")
def o_topk(s, d):
    return t(s, d, "part").select(F.col("p_partkey").alias("k"), F.col("p_retailprice").alias("v")).orderBy(F.desc("v"), "k").limit(10)


@entry("SELECT p_brand AS b, p_partkey AS k FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 2")
def o_topk_group(s, d):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t(s, d, "part").withColumn("rn", F.row_number().over(w)).where("rn <= 2").select(F.col("p_brand").alias("b"), F.col("p_partkey").alias("k"))


@entry("SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 9000 UNION SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000")
def o_set_union(s, d):
    return _rich(s, d)[0].union(_rich(s, d)[1]).distinct()


@entry("SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 9000 INTERSECT SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000")
def o_set_intersect(s, d):
    return _rich(s, d)[0].intersect(_rich(s, d)[1])


@entry("SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 9000 EXCEPT ALL SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000")
def o_set_except_all(s, d):
    return _rich(s, d)[0].exceptAll(_rich(s, d)[1])


def _rich(s, d):
    return t(s, d, "customer").where("c_acctbal > 9000").select(F.col("c_nationkey").alias("k")), t(s, d, "supplier").where("s_acctbal > 5000").select(F.col("s_nationkey").alias("k"))


@entry("SELECT page_id AS k, lower(regexp_extract(url, '://([^/]+)', 1)) AS h, length(html) AS n FROM pages")
def o_string(s, d):
    return t(s, d, "pages").select(F.col("page_id").alias("k"), F.lower(F.regexp_extract("url", "://([^/]+)", 1)).alias("h"), F.length("html").cast("long").alias("n"))


@entry("SELECT a.p_brand AS a, b.p_brand AS b, levenshtein(a.p_brand, b.p_brand) AS v FROM (SELECT DISTINCT p_brand FROM part) a JOIN (SELECT DISTINCT p_brand FROM part) b ON a.p_brand < b.p_brand AND a.p_brand[-1] = b.p_brand[-1]")
def o_levenshtein(s, d):
    """Edit distance within blocks of the same last character."""
    b = t(s, d, "part").select("p_brand").distinct().withColumn("e", F.expr("right(p_brand, 1)"))
    return b.select("e", F.col("p_brand").alias("a")).join(b.select("e", F.col("p_brand").alias("b")), "e").where("a < b").select("a", "b", F.levenshtein("a", "b").cast("long").alias("v"))


@entry("SELECT o_orderkey AS k, year(o_orderdate) AS y, quarter(o_orderdate) AS q, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS n FROM orders")
def o_date(s, d):
    c = F.col("o_orderdate")
    return t(s, d, "orders").select(F.col("o_orderkey").alias("k"), F.year(c).cast("long").alias("y"), F.quarter(c).cast("long").alias("q"), F.datediff(c, F.lit("1995-01-01")).cast("long").alias("n"))


@entry("SELECT l_orderkey AS k, l_linenumber AS ln, round(l_extendedprice / nullif(l_discount, 0), 2) AS v, floor(l_quantity / 7) AS f FROM lineitem")
def o_math(s, d):
    return t(s, d, "lineitem").select(F.col("l_orderkey").alias("k"), F.col("l_linenumber").alias("ln"), F.round(F.try_divide("l_extendedprice", "l_discount"), 2).alias("v"), F.floor(F.col("l_quantity") / 7).cast("double").alias("f"))


@entry("SELECT doc_id AS k, len(list_filter(string_split(text, ' '), lambda x: length(x) > 5)) AS n FROM documents")
def o_array(s, d):
    return t(s, d, "documents").select(F.col("doc_id").alias("k"), F.size(F.filter(F.split("text", " "), lambda x: F.length(x) > 5)).cast("long").alias("n"))


@entry("SELECT event_type AS t, round(avg(CAST(json_extract_string(props, '$.k') AS DOUBLE)), 4) AS k FROM events GROUP BY 1")
def o_json(s, d):
    return t(s, d, "events").groupBy(F.col("event_type").alias("t")).agg(F.round(F.avg(F.from_json("props", "k double")["k"]), 4).alias("k"))


@entry("SELECT r_name AS r, string_agg(n_name, ',' ORDER BY n_name) AS l FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def o_listagg(s, d):
    return t(s, d, "nation").join(F.broadcast(t(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).groupBy(F.col("r_name").alias("r")).agg(F.array_join(F.sort_array(F.collect_list("n_name")), ",").alias("l"))


@entry("WITH RECURSIVE a(n, p) AS (SELECT 1, 1 UNION ALL SELECT n + 1, p * (n + 1) FROM a WHERE n < 8) SELECT n, p FROM a")
def o_recursive(s, d):
    return s.sql(ORACLES["o_recursive"])


@entry("SELECT c_custkey AS k FROM customer c WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer e WHERE e.c_mktsegment = c.c_mktsegment)")
def o_correlated(s, d):
    t(s, d, "customer").createOrReplaceTempView("customer")
    return s.sql(ORACLES["o_correlated"])


@entry("SELECT o_orderkey AS k FROM orders WHERE (o_orderkey * 7919) % 100 < 5")
def o_sample_hash(s, d):
    return t(s, d, "orders").where("(o_orderkey * 7919) % 100 < 5").select(F.col("o_orderkey").alias("k"))


@entry("SELECT o_orderstatus AS s, count(*) AS n FROM orders WHERE o_totalprice > 1000 GROUP BY 1")
def o_pipe_sql(s, d):
    t(s, d, "orders").createOrReplaceTempView("orders")
    return s.sql("FROM orders |> WHERE o_totalprice > 1000 |> AGGREGATE count(*) AS n GROUP BY o_orderstatus AS s")


@entry("SELECT vec_id AS k, round(list_cosine_similarity(CAST(embedding AS DOUBLE[]), (SELECT CAST(embedding AS DOUBLE[]) FROM embeddings WHERE vec_id = 0)), 5) AS c FROM embeddings")
def v_cosine(s, d):
    e = t(s, d, "embeddings").select(F.col("vec_id").alias("k"), F.col("embedding").cast("array<double>").alias("x"))
    one = F.broadcast(e.where("k = 0").select(F.col("x").alias("y")))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda u, v: u + v)
    return e.join(one).select("k", F.round(dot("x", "y") / F.sqrt(dot("x", "x") * dot("y", "y")), 5).alias("c"))


@entry("SELECT label, pos, round(avg(v), 5) AS m FROM (SELECT label, unnest(range(len(embedding))) AS pos, unnest(CAST(embedding AS DOUBLE[])) AS v FROM embeddings) GROUP BY 1, 2")
def v_mean_init(s, d):
    """Mean of the vectors that belong to a token, position by position."""
    return t(s, d, "embeddings").select("label", F.posexplode(F.col("embedding").cast("array<double>")).alias("pos", "v")).groupBy("label", F.col("pos").cast("long").alias("pos")).agg(F.round(F.avg("v"), 5).alias("m"))


@entry("SELECT vec_id AS k, round(exp(embedding[2]) / list_sum(list_transform(embedding[2:34], lambda x: exp(CAST(x AS DOUBLE)))), 6) AS p FROM embeddings")
def v_constrained(s, d):
    """Probability of the first error token when only positions 1 to 33 compete."""
    x = F.col("embedding").cast("array<double>")
    return t(s, d, "embeddings").select(F.col("vec_id").alias("k"), F.round(F.exp(x[1]) / F.aggregate(F.transform(F.slice(x, 2, 33), F.exp), F.lit(0.0), lambda a, b: a + b), 6).alias("p"))


@entry("SELECT o_orderpriority AS p, round(avg(o_totalprice), 4) AS m FROM orders GROUP BY 1")
def u_grouped_udaf(s, d):
    @F.pandas_udf("double")
    def mean(v: pd.Series) -> float:
        return float(v.mean())

    return t(s, d, "orders").groupBy(F.col("o_orderpriority").alias("p")).agg(F.round(mean("o_totalprice"), 4).alias("m"))


@entry(" UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS n FROM {n}" for n in TABLES))
def o_scan_parquet(s, d):
    return reduce(DataFrame.unionAll, [t(s, d, n).agg(F.count("*").alias("n")).select(F.lit(n).alias("name"), "n") for n in TABLES])


@entry("SELECT user_id AS u, string_agg(event_type || '=' || n, ',' ORDER BY event_type) AS m FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1")
def o_map(s, d):
    """Counts of each user as a map, shown by sorted keys."""
    each = t(s, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    made = each.groupBy(F.col("user_id").alias("u")).agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return made.select("u", F.array_join(F.transform(F.array_sort(F.map_keys("m")), lambda k: F.concat(k, F.lit("="), F.col("m")[k].cast("string"))), ",").alias("m"))


@entry("SELECT doc_id AS k, CAST(i AS BIGINT) AS i, length(w) AS n FROM (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS w, unnest(range(1, len(string_split(coalesce(text, ''), chr(10))) + 1)) AS i FROM documents)")
def o_lateral(s, d):
    """Lines of each document by a lateral generator."""
    t(s, d, "documents").createOrReplaceTempView("lateral_documents")
    return s.sql(r"SELECT doc_id AS k, CAST(pos + 1 AS BIGINT) AS i, CAST(length(line) AS BIGINT) AS n FROM lateral_documents, LATERAL posexplode(split(coalesce(text, ''), '\n', -1)) AS x(pos, line)")


@entry("SELECT c_custkey AS k FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer)")
def o_scalar_subquery(s, d):
    t(s, d, "customer").createOrReplaceTempView("customer")
    return s.sql(ORACLES["o_scalar_subquery"])


@entry("SELECT vec_id AS k, round(sqrt(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * x))), 5) AS length, round(list_cosine_similarity(CAST(embedding AS DOUBLE[]), [1.0] || list_transform(range(len(embedding) - 1), lambda i: 0.0)), 5) AS first FROM embeddings")
def u_pandas_cosine(s, d):
    """Length, and cosine with the first axis, in Arrow batches."""

    @F.pandas_udf("length double, first double")
    def measure(v: pd.Series) -> pd.DataFrame:
        x = np.stack(v.to_numpy()).astype(float)
        size = np.sqrt((x * x).sum(1))
        return pd.DataFrame({"length": size, "first": x[:, 0] / size})

    return t(s, d, "embeddings").select(F.col("vec_id").alias("k"), measure("embedding").alias("m")).select("k", F.round("m.length", 5).alias("length"), F.round("m.first", 5).alias("first"))


@entry("SELECT q.vec_id AS q, e.vec_id AS k, CAST(row_number() OVER (PARTITION BY q.vec_id ORDER BY round(list_cosine_similarity(CAST(q.embedding AS DOUBLE[]), CAST(e.embedding AS DOUBLE[])), 9) DESC, e.vec_id) AS BIGINT) AS place FROM embeddings q JOIN embeddings e ON q.label = e.label AND q.vec_id <> e.vec_id WHERE q.vec_id % 100 = 0 QUALIFY place <= 3")
def v_knn(s, d):
    """Examples for few-shot prompts: the three nearest of a query's own label.
    Queries are the rows whose id is divisible by 100, against all rows; each
    task keeps its best three of a query before the shuffle."""
    e = t(s, d, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("x"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda u, v: u + v)
    q = e.where("vec_id % 100 = 0").select(F.col("vec_id").alias("q"), "label", F.col("x").alias("y"))
    both = e.join(q, "label").where("vec_id <> q").select("q", F.col("vec_id").alias("k"), F.round(dot("x", "y") / F.sqrt(dot("x", "x") * dot("y", "y")), 9).alias("c"))
    place = Window.partitionBy("q").orderBy(F.desc("c"), "k")
    return both.withColumn("place", F.row_number().over(place).cast("long")).where("place <= 3").select("q", "k", "place")


_TEXTS = [("a", "SELECT x, COUNT(*) FROM t WHERE y = 3"), ("b", "SELECT 1"), ("c", "not ; a query")]


@entry("SELECT * FROM (VALUES ('a', 13, 3), ('b', 2, 1), ('c', 4, 1)) AS v(k, tokens, words)")
def u_udtf_tokens(s, d):
    """Tokens of queries by a table function in a lateral join."""
    from ..sqltree import register_all

    register_all(s)
    s.createDataFrame(_TEXTS, "k string, q string").createOrReplaceTempView("udtf_texts")
    return s.sql("SELECT k, CAST(count(*) AS INT) AS tokens, CAST(count_if(kind = 'word') AS INT) AS words FROM udtf_texts, LATERAL sql_tokens(q) GROUP BY k")


@entry("SELECT * FROM (VALUES ('a', 'SELECT x, COUNT(*) FROM t WHERE y = 3'), ('b', 'SELECT 1'), ('c', 'not ; a query')) AS v(k, q)")
def u_udf_render(s, d):
    """Parsed to JSON and rendered again; what does not parse comes back as it is."""
    from ..sqltree import register_all

    register_all(s)
    s.createDataFrame(_TEXTS, "k string, q string").createOrReplaceTempView("udf_texts")
    return s.sql("SELECT k, render_sql(parse_sql_json(q)) AS q FROM udf_texts")


#: Measures need an outcomes table. This one is made of documents and labels: the
#: query is "wrong" where quality is 0, "flagged" where the text is short, "mended"
#: where it is not toxic, "changed" where it is not English.
_OUT = "SELECT CASE WHEN doc_id % 2 = 0 THEN 'even' ELSE 'odd' END AS method, lang AS level, quality = 0 AS truth_wrong, n_chars < 700 AS flagged, toxic = 0 AS refined_equals_gold, lang <> 'en' AS changed_result, quality = 1 OR toxic = 0 AS ex, source = 'src1' AS failed FROM documents JOIN labels USING (doc_id)"


def _outcomes(s, d):
    docs, labels = t(s, d, "documents"), t(s, d, "labels")
    wrong, toxic = F.col("quality") == 0, F.col("toxic") == 0
    return docs.join(labels, "doc_id").select(
        F.when(F.col("doc_id") % 2 == 0, "even").otherwise("odd").alias("method"), F.col("lang").alias("level"), wrong.alias("truth_wrong"), (F.col("n_chars") < 700).alias("flagged"), toxic.alias("refined_equals_gold"),
        (F.col("lang") != "en").alias("changed_result"), ((F.col("quality") == 1) | toxic).alias("ex"), (F.col("source") == "src1").alias("failed"),
    )


@entry(f"SELECT method, count(*) FILTER (truth_wrong AND flagged) AS tp, count(*) FILTER (truth_wrong AND flagged AND refined_equals_gold) AS fixed, round(count(*) FILTER (truth_wrong AND flagged AND refined_equals_gold) / nullif(count(*) FILTER (truth_wrong AND flagged), 0), 6) AS fixed_rate FROM ({_OUT}) GROUP BY 1")
def m_fixed_rate(s, d):
    return metrics.fixed_rate(_outcomes(s, d))


@entry(f"SELECT method, count(*) FILTER (NOT truth_wrong AND flagged) AS fp, count(*) FILTER (NOT truth_wrong AND flagged AND changed_result) AS corrupted, round(count(*) FILTER (NOT truth_wrong AND flagged AND changed_result) / nullif(count(*) FILTER (NOT truth_wrong AND flagged), 0), 6) AS corruption_rate FROM ({_OUT}) GROUP BY 1")
def m_corruption_rate(s, d):
    return metrics.corruption_rate(_outcomes(s, d))


@entry(f"SELECT method, count(*) AS questions, count(*) FILTER (truth_wrong AND flagged AND refined_equals_gold) AS fixed, count(*) FILTER (NOT truth_wrong AND flagged AND changed_result) AS corrupted, round((count(*) FILTER (truth_wrong AND flagged AND refined_equals_gold) - count(*) FILTER (NOT truth_wrong AND flagged AND changed_result)) / count(*), 6) AS gain_parts, round((count(*) FILTER (ex) - count(*) FILTER (NOT truth_wrong)) / count(*), 6) AS gain_direct FROM ({_OUT}) GROUP BY 1")
def m_decompose(s, d):
    return metrics.decompose_gain(_outcomes(s, d))


@entry(f"SELECT method, count(*) FILTER (truth_wrong) AS wrong, count(*) FILTER (truth_wrong AND failed) AS failing, round(count(*) FILTER (truth_wrong AND failed) / nullif(count(*) FILTER (truth_wrong), 0), 6) AS share FROM ({_OUT}) GROUP BY 1")
def m_explicit_failures(s, d):
    return metrics.explicit_failure_share(_outcomes(s, d), ("method",))


#: Types from the counts of characters: truth one or two slots, found another rule.
_TYPED = "SELECT [CAST(doc_id % 14 + 1 AS INT)] AS truth_types, [CAST(n_chars % 14 + 1 AS INT), CAST(doc_id % 7 + 1 AS INT)] AS types FROM documents"


def _typed(s, d):
    slot = lambda c, k: (F.col(c) % k + 1).cast("int")
    return t(s, d, "documents").select(F.lit("m").alias("method"), F.array(slot("doc_id", 14)).alias("truth_types"), F.array(slot("n_chars", 14), slot("doc_id", 7)).alias("types"))


@entry(f"SELECT truth_types[1] AS slot, count(*) AS cases, round(avg(CASE WHEN list_contains(types, truth_types[1]) THEN 1.0 ELSE 0 END), 6) AS tsa FROM ({_TYPED}) GROUP BY 1")
def m_type_accuracy(s, d):
    return metrics.type_specific_accuracy(_typed(s, d))


@entry("WITH c AS (SELECT * FROM (VALUES " + ", ".join(f"({slot}, '{name}')" for slot, name in sorted(CATEGORY_OF.items())) + f") AS v(slot, category)), x AS (SELECT row_number() OVER () AS i, truth_types[1] AS truth, types FROM ({_TYPED})), f AS (SELECT i, truth, unnest(types) AS found FROM x) SELECT 'm' AS method, a.category, count(DISTINCT i) AS cases, round(count(DISTINCT CASE WHEN a.category = b.category THEN i END) / count(DISTINCT i), 6) AS tsa FROM f JOIN c a ON a.slot = f.truth JOIN c b ON b.slot = f.found GROUP BY 2")
def m_category_accuracy(s, d):
    return metrics.category_accuracy(_typed(s, d), CATEGORY_OF)


@entry("SELECT round(corr(quality - n_chars / 1000.0, toxic + n_chars / 3000.0), 6) AS r FROM documents JOIN labels USING (doc_id)")
def m_drop_correlation(s, d):
    both = t(s, d, "documents").join(t(s, d, "labels"), "doc_id")
    return metrics.drop_correlation(both.select((F.col("quality") - F.col("n_chars") / 1000.0).alias("f1_drop"), (F.col("toxic") + F.col("n_chars") / 3000.0).alias("ex_drop")))


#: Relational detection: short documents are flagged, low quality is the truth.
_FLAGS = "SELECT n_chars < 400 AS f, quality = 0 AS w FROM documents JOIN labels USING (doc_id)"


@entry(f"SELECT 'short' AS method, CAST(sum(CASE WHEN f AND w THEN 1 ELSE 0 END) AS BIGINT) AS tp, CAST(sum(CASE WHEN f AND NOT w THEN 1 ELSE 0 END) AS BIGINT) AS fp, CAST(sum(CASE WHEN NOT f AND w THEN 1 ELSE 0 END) AS BIGINT) AS fn, CAST(sum(CASE WHEN NOT f AND NOT w THEN 1 ELSE 0 END) AS BIGINT) AS tn, round(sum(CASE WHEN f AND w THEN 1.0 ELSE 0 END) / sum(CASE WHEN f THEN 1.0 ELSE 0 END), 6) AS precision, round(sum(CASE WHEN f AND w THEN 1.0 ELSE 0 END) / sum(CASE WHEN w THEN 1.0 ELSE 0 END), 6) AS recall, round(sum(CASE WHEN f = w THEN 1.0 ELSE 0 END) / count(*), 6) AS accuracy, round(2 * sum(CASE WHEN f AND w THEN 1.0 ELSE 0 END) / (sum(CASE WHEN f THEN 1.0 ELSE 0 END) + sum(CASE WHEN w THEN 1.0 ELSE 0 END)), 6) AS f1 FROM ({_FLAGS})")
def m_detection(s, d):
    return metrics.detection_report(t(s, d, "documents").join(t(s, d, "labels"), "doc_id").select(F.lit("short").alias("method"), (F.col("quality") == 0).alias("truth_wrong"), (F.col("n_chars") < 400).alias("flagged")))


@entry("SELECT lang AS level, count(*) AS questions, round(avg(CASE WHEN quality = 1 THEN 1.0 ELSE 0 END), 6) AS ex, 'all' AS method FROM documents JOIN labels USING (doc_id) GROUP BY lang UNION ALL SELECT NULL, count(*), round(avg(CASE WHEN quality = 1 THEN 1.0 ELSE 0 END), 6), 'all' FROM documents JOIN labels USING (doc_id)")
def m_execution_accuracy(s, d):
    return metrics.execution_accuracy(t(s, d, "documents").join(t(s, d, "labels"), "doc_id").select(F.lit("all").alias("method"), F.col("lang").alias("level"), (F.col("quality") == 1).alias("ex")))
