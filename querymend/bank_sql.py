"""The gold workload: one representative of each template, by name. Text is
shared by both engines but for two templates."""

from __future__ import annotations

#: Name -> SQL.
WORKLOAD = {
    "w_01": """SELECT COUNT(*) AS n FROM orders WHERE o_orderpriority = '1-URGENT'""",
    "w_02": """SELECT c_custkey AS k, c_name AS name FROM customer WHERE c_mktsegment = 'BUILDING' AND c_acctbal > 9000""",
    "w_03": """SELECT p_partkey AS k, p_retailprice AS price FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 5""",
    "w_04": """SELECT DISTINCT p_brand AS brand FROM part WHERE p_size >= 45""",
    "w_05": """SELECT c_mktsegment AS seg, ROUND(AVG(c_acctbal), 2) AS bal FROM customer GROUP BY c_mktsegment""",
    "w_06": """SELECT COUNT(*) AS n FROM orders WHERE YEAR(o_orderdate) = 1997""",
    "w_07": """SELECT COUNT(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'EUROPE'""",
    "w_08": """SELECT n_name AS nation, ROUND(SUM(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name""",
    "w_09": """SELECT o_custkey AS k, COUNT(*) AS n FROM orders GROUP BY o_custkey HAVING COUNT(*) > 15""",
    "w_10": """SELECT l_returnflag AS f, l_linestatus AS s, ROUND(SUM(l_quantity), 2) AS qty, ROUND(SUM(l_extendedprice), 2) AS price, ROUND(SUM(l_extendedprice * (1 - l_discount)), 2) AS disc_price, ROUND(AVG(l_discount), 6) AS avg_disc, MAX(l_tax) AS max_tax, COUNT(*) AS n FROM lineitem GROUP BY l_returnflag, l_linestatus""",
    "w_11": """SELECT c_custkey AS k FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')""",
    "w_12": """SELECT p_partkey AS k FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_returnflag = 'R' AND l_quantity >= 48)""",
    "w_13": """SELECT n_nationkey AS k FROM nation WHERE EXISTS (SELECT 1 FROM supplier WHERE s_nationkey = n_nationkey AND s_acctbal > 9000) AND EXISTS (SELECT 1 FROM customer JOIN orders ON o_custkey = c_custkey WHERE c_nationkey = n_nationkey AND o_orderpriority = '1-URGENT')""",
    "w_14": """SELECT YEAR(o_orderdate) AS y, ROUND(AVG(CASE WHEN o_orderpriority = '1-URGENT' THEN 1.0E0 ELSE 0.0E0 END), 6) AS share FROM orders GROUP BY YEAR(o_orderdate)""",
    "w_15": """SELECT ROUND(100 * SUM(CASE WHEN p_type = 'PROMO' THEN l_extendedprice * (1 - l_discount) ELSE 0.0E0 END) / SUM(l_extendedprice * (1 - l_discount)), 4) AS promo FROM lineitem JOIN part ON l_partkey = p_partkey""",
    "w_16": """SELECT k, ok, price FROM (SELECT o_custkey AS k, o_orderkey AS ok, o_totalprice AS price, ROW_NUMBER() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) AS t WHERE rn = 1""",
    "w_17": """SELECT o_custkey AS k, o_orderkey AS ok, ROUND(SUM(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 2) AS running FROM orders""",
    "w_18": """SELECT c.c_custkey AS k FROM customer AS c WHERE c.c_acctbal > (SELECT AVG(d.c_acctbal) FROM customer AS d WHERE d.c_mktsegment = c.c_mktsegment)""",
    "w_19": """SELECT y, m, n, n - LAG(n) OVER (ORDER BY y, m) AS growth FROM (SELECT YEAR(o_orderdate) AS y, MONTH(o_orderdate) AS m, COUNT(*) AS n FROM orders GROUP BY YEAR(o_orderdate), MONTH(o_orderdate)) AS t""",
    "w_20": """SELECT brand, k, rk FROM (SELECT p_brand AS brand, p_partkey AS k, RANK() OVER (PARTITION BY p_brand ORDER BY SUM(l_quantity) DESC, p_partkey) AS rk FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand, p_partkey) AS t WHERE rk <= 3""",
    "w_21": """SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 9000 EXCEPT SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000""",
    "w_22": """SELECT r_name AS region, n_name AS nation, ROUND(SUM(c_acctbal), 2) AS bal FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)""",
    "w_23": """SELECT c_mktsegment AS seg, r_name AS region, COUNT(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (c_mktsegment, r_name)""",
    "w_24": """SELECT COUNT(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_shipdate > o_orderdate + INTERVAL '60' DAY""",
    "w_25": """SELECT CAST(ts AS DATE) AS d, event_type AS t, COUNT(*) AS n FROM events GROUP BY CAST(ts AS DATE), event_type""",
    "w_26": """SELECT a.event_id AS s, b.event_id AS e FROM events AS a JOIN events AS b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL '60' MINUTE WHERE a.event_type = 'signup' AND b.event_type = 'error'""",
    "w_27": """SELECT event_type AS t, ROUND(AVG(CAST(get_json_object(props, '$.k') AS DOUBLE)), 4) AS k FROM events GROUP BY event_type""",
    "w_28": """SELECT lang, COUNT(*) AS n FROM documents WHERE n_chars > 1000 GROUP BY lang""",
    "w_29": """SELECT source AS src, ROUND(AVG(1.0E0 - quality), 6) AS low FROM labels JOIN documents ON labels.doc_id = documents.doc_id GROUP BY source""",
    "w_30": """SELECT conv_id AS c, COUNT(*) AS turns FROM conversations GROUP BY conv_id ORDER BY COUNT(*) DESC, conv_id LIMIT 5""",
    "w_31": """SELECT REGEXP_EXTRACT(url, '^https?://([^/]+)', 1) AS host, COUNT(*) AS n FROM pages GROUP BY REGEXP_EXTRACT(url, '^https?://([^/]+)', 1)""",
    "w_32": """SELECT DISTINCT b.item_id AS k FROM benchmark AS b JOIN documents AS d ON CONTAINS(d.text, b.text)""",
    "w_33": """SELECT label, pos, ROUND(AVG(CAST(v AS DOUBLE)), 4) AS m FROM embeddings LATERAL VIEW POSEXPLODE(embedding) AS pos, v GROUP BY label, pos""",
}
#: The two that differ, for DuckDB.
DUCKDB = {
    "w_27": """SELECT event_type AS t, ROUND(AVG(CAST(json_extract_string(props, '$.k') AS DOUBLE)), 4) AS k FROM events GROUP BY event_type""",
    "w_33": """SELECT label, pos, ROUND(AVG(CAST(v AS DOUBLE)), 4) AS m FROM (SELECT label, UNNEST(RANGE(LEN(embedding))) AS pos, UNNEST(embedding) AS v FROM embeddings) AS t GROUP BY label, pos""",
}

#: Wrong queries with their questions and gold, by name and slots.
CASES = {
    "f01": ([1], """How many orders did customers of the BUILDING segment place?""", """SELECT COUNT(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING'""", """SELECT COUNT(*) AS n FROM orders WHERE c_mktsegment = 'BUILDING'"""),
    "f02": ([2], """What is the total balance per market segment?""", """SELECT c_mktsegment AS seg, ROUND(SUM(c_acctbal), 2) AS bal FROM customer GROUP BY c_mktsegment""", """SELECT c_mktsegment AS seg, ROUND(SUM(c_acctbal), 2) AS bal FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY c_mktsegment"""),
    "f03": ([3], """How many suppliers have a balance below zero?""", """SELECT COUNT(*) AS n FROM supplier WHERE s_acctbal < 0""", """SELECT COUNT(*) AS n FROM customer WHERE c_acctbal < 0"""),
    "f04": ([4], """How many returned lines belong to parts of size 11?""", """SELECT COUNT(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_size = 11 AND l_returnflag = 'R'""", """SELECT COUNT(*) AS n FROM lineitem JOIN part ON l_suppkey = p_partkey WHERE p_size = 11 AND l_returnflag = 'R'"""),
    "f05": ([5], """List the name and balance of suppliers of nation 3.""", """SELECT s_name AS name, s_acctbal AS bal FROM supplier WHERE s_nationkey = 3""", """SELECT s_name AS name FROM supplier WHERE s_nationkey = 3"""),
    "f06": ([6], """List the names of suppliers of nation 3.""", """SELECT s_name AS name FROM supplier WHERE s_nationkey = 3""", """SELECT s_name AS name, s_suppkey AS k FROM supplier WHERE s_nationkey = 3"""),
    "f07": ([7], """What is the total quantity per return flag?""", """SELECT l_returnflag AS f, ROUND(SUM(l_quantity), 2) AS q FROM lineitem GROUP BY l_returnflag""", """SELECT l_returnflag AS f, ROUND(SUM(l_extendedprice), 2) AS q FROM lineitem GROUP BY l_returnflag"""),
    "f08": ([8], """How many customers are in the MACHINERY segment?""", """SELECT COUNT(*) AS n FROM customer WHERE c_mktsegment = 'MACHINERY'""", """SELECT COUNT(*) AS n FROM customer WHERE c_mktsegment = 'machinery'"""),
    "f09": ([9], """How many urgent orders are open?""", """SELECT COUNT(*) AS n FROM orders WHERE o_orderpriority = '1-URGENT' AND o_orderstatus = 'O'""", """SELECT COUNT(*) AS n FROM orders WHERE o_orderpriority = '1-URGENT'"""),
    "f10": ([10], """How many events are clicks or views?""", """SELECT COUNT(*) AS n FROM events WHERE event_type = 'click' OR event_type = 'view'""", """SELECT COUNT(*) AS n FROM events WHERE event_type = 'click' AND event_type = 'view'"""),
    "f11": ([11], """What is the average retail price per part type?""", """SELECT p_type AS t, ROUND(AVG(p_retailprice), 2) AS v FROM part GROUP BY p_type""", """SELECT p_type AS t, ROUND(MAX(p_retailprice), 2) AS v FROM part GROUP BY p_type"""),
    "f12": ([12], """Which three parts have the highest retail price?""", """SELECT p_partkey AS k, p_retailprice AS v FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 3""", """SELECT p_partkey AS k, p_retailprice AS v FROM part ORDER BY p_retailprice, p_partkey LIMIT 3"""),
    "f13": ([13], """How many parts were never returned?""", """SELECT COUNT(*) AS n FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R')""", """SELECT COUNT(*) AS n FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R')"""),
    "f14": ([14], """How many lines have a quantity of at least 30?""", """SELECT COUNT(*) AS n FROM lineitem WHERE l_quantity >= 30""", """SELECT COUNT(*) AS n FROM lineitem WHERE l_quantity > 30"""),
    "f15": ([1, 9], """How many open orders did AUTOMOBILE customers place?""", """SELECT COUNT(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'AUTOMOBILE' AND o_orderstatus = 'O'""", """SELECT COUNT(*) AS n FROM orders WHERE c_mktsegment = 'AUTOMOBILE'"""),
    "f16": ([7, 12], """What is the total order price per status?""", """SELECT o_orderstatus AS s, ROUND(SUM(o_totalprice), 2) AS v FROM orders GROUP BY o_orderstatus""", """SELECT o_orderpriority AS s, ROUND(SUM(o_totalprice), 2) AS v FROM orders GROUP BY o_orderstatus"""),
    "f17": ([], """How many nations lie in ASIA?""", """SELECT COUNT(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA'""", """SELECT COUNT(*) AS n FROM nation AS a JOIN region AS b ON b.r_regionkey = a.n_regionkey WHERE b.r_name = 'ASIA'"""),
    "f18": ([], """How many orders are there?""", """SELECT COUNT(*) AS n FROM orders""", """SELECT COUNT(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey"""),
}
