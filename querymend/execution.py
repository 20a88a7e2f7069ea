"""Running queries: databases as sessions, outcomes, result fingerprints.

A database is a folder of Parquet tables. ``open_db`` gives it a session of its
own, so that the views of two folders never mix. Two results are compared by
one-row fingerprints: order-free sums and xors of two independent row hashes."""

from __future__ import annotations

import logging
import re
from collections.abc import Iterable
from concurrent.futures import Future, ThreadPoolExecutor
from dataclasses import dataclass
from threading import Lock

from py4j.protocol import Py4JJavaError
from pyspark import StorageLevel
from pyspark.errors import PySparkException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import workspace
from .sqltree import Node, parse

TABLES = "region nation customer supplier part orders lineitem events documents labels conversations pages benchmark embeddings".split()
#: A candidate that fails is a result here; its message needs no log line.
logging.getLogger("SQLQueryContextLogger").setLevel(logging.CRITICAL)
#: Bytes of a database for each shuffle partition of its session.
PARTITION_BYTES = 64 << 20
#: Most queries that share a scan, and the aggregates that they may have.
SCANS, TOTALS = 12, {"COUNT", "SUM", "AVG", "MIN", "MAX"}
#: Tables of which a witness has a part.
DRAWN = ("orders", "lineitem", "events", "customer", "part", "supplier")


def register_db(spark: SparkSession, sf_dir: str, tables: Iterable[str] = TABLES) -> None:
    """Temporary views over the Parquet tables of one database folder."""
    for name in tables:
        spark.read.parquet(f"{sf_dir}/{name}.parquet").createOrReplaceTempView(name)


def folder_bytes(spark: SparkSession, path: str) -> int:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(at).getLength()


def open_db(spark: SparkSession, sf_dir: str, tables: Iterable[str] = TABLES[:9]) -> SparkSession:
    """A session of its own with the folder's tables as views; its number of
    shuffle partitions follows their bytes."""
    db = spark.newSession()
    register_db(db, sf_dir, tables)
    size = sum(folder_bytes(spark, f"{sf_dir}/{t}.parquet") for t in tables)
    db.conf.set("spark.sql.shuffle.partitions", str(max(1, -(-size // PARTITION_BYTES))))
    db.conf.set("spark.sql.session.timeZone", "UTC")
    db.conf.set("spark.sql.ui.explainMode", "simple")  # plans of thousands of queries are not shown
    return db


def interpreted(db: SparkSession) -> SparkSession:
    """The session of a small database: compiling a query and planning it anew
    take longer than its rows."""
    for k, v in (("adaptive.enabled", "false"), ("codegen.wholeStage", "false"), ("codegen.factoryMode", "NO_CODEGEN")):
        db.conf.set(f"spark.sql.{k}", v)
    return db


def by_keys(sql: str, everywhere: bool = False) -> str:
    """The query with ``x NOT IN (subquery)`` below an OR as tests of existence.
    Spark joins such a place by nested loops, every row with every value, as either
    may be null; nulls are told apart here, and values are joined by equality.
    ``everywhere``: in other places of a WHERE as well. Spark gives all values of
    these to each executor, which has no room for those of a large table."""
    if not re.search(r"\bNOT\s+IN\s*\(\s*SELECT\b", sql, re.I):
        return sql
    out = sql

    def places(n: Node, either: bool = False, sure: bool = False) -> list[tuple[Node, bool]]:
        """With whether a row is kept only if the test holds, so that false and
        null are alike."""
        if (either or everywhere) and n.role == "in" and n.value == "NOT " and n.kids[0].role == "column" and n.kids[1].role == "query":
            return [(n, sure)]
        own = n.role == "where" or sure and (n.role == "paren" or n.role == "bool" and n.value == "AND")
        return [x for k in n.kids for x in places(k, (either or n.role == "bool" and n.value == "OR") and n.role != "query", own)]

    for n, sure in sorted(places(parse(sql)), key=lambda p: -p[0].start):
        x, values = (sql[k.start : k.stop] for k in n.kids)
        values = f"(\n{by_keys(values, True) if everywhere else values}\n) AS values__(value__)"
        if sure:
            test = f"NOT EXISTS (SELECT 1 FROM {values} WHERE value__ = {x}) AND NOT EXISTS (SELECT 1 FROM {values} WHERE value__ IS NULL) AND ({x} IS NOT NULL OR NOT EXISTS (SELECT 1 FROM {values}))"
        else:
            test = f"CASE WHEN EXISTS (SELECT 1 FROM {values} WHERE value__ = {x}) THEN FALSE WHEN {x} IS NULL AND EXISTS (SELECT 1 FROM {values}) OR EXISTS (SELECT 1 FROM {values} WHERE value__ IS NULL) THEN NULL ELSE TRUE END"
        out = out[: n.start] + test + out[n.stop :]
    return out


def feedback(spark: SparkSession, sql: str, level: str = "analyze") -> dict:
    """Outcome of a query up to ``level``: parse, analyze (no data is read) or full."""
    out = {"status": "ok", "stage": level, "error_class": None, "sqlstate": None, "start": None, "stop": None, "params": {}}
    try:
        if level == "parse":
            spark._jsparkSession.sessionState().sqlParser().parsePlan(sql)
        else:
            df = spark.sql(sql)
            df.schema  # noqa: B018 - forces analysis
            if level == "full":
                df.write.format("noop").mode("overwrite").save()
    except PySparkException as e:
        context = e.getQueryContext() or []
        spot = context[0] if context else None
        out |= {"status": "failed", "error_class": e.getCondition(), "sqlstate": e.getSqlState(), "params": dict(e.getMessageParameters() or {})}
        if spot is not None and spot.startIndex() >= 0:
            out |= {"start": spot.startIndex(), "stop": spot.stopIndex() + 1}
    except Py4JJavaError:
        out |= {"status": "failed", "error_class": "EXECUTION"}
    return out


def plan_key(spark: SparkSession, sql: str) -> str | None:
    """Text of the optimized plan with expression ids numbered anew: queries
    with one key return the same rows. None if the query does not analyse."""
    try:
        plan = spark.sql(sql)._jdf.queryExecution().optimizedPlan().canonicalized().toString()
    except (PySparkException, Py4JJavaError):
        return None
    seen: dict[str, str] = {}
    return re.sub(r"#\d+L?", lambda m: seen.setdefault(m[0], f"#{len(seen)}"), plan)


def canonical(field: T.StructField, digits: int = 12, whole: int = 11) -> str:
    """A cell as text (an SQL expression), so that equal values of different
    number types agree.

    Integers and decimals are compared exactly. Doubles that are a whole number
    in ``whole`` digits are that number; others agree in ``digits`` significant
    ones, as sums of doubles depend on the order of their terms. -0.0 is 0, NaN is
    NaN."""
    c, kind = f"`{field.name}`", field.dataType
    if isinstance(kind, (T.DoubleType, T.FloatType)) or isinstance(kind, T.DecimalType) and kind.scale > 0:
        x = f"CAST({c} AS DOUBLE)"
        near = f"abs({x}) < 9.0e15D AND abs({x} - rint({x})) <= abs({x}) * 1e-{whole}D"
        text = f"CASE WHEN isnan({x}) THEN 'NaN' WHEN {near} THEN CAST(CAST(rint({x}) AS BIGINT) AS STRING) WHEN {x} IS NOT NULL THEN format_string('%.{digits - 1}e', {x}) END"
    elif isinstance(kind, (T.ArrayType, T.StructType, T.MapType)):
        text = f"to_json({c})"
    else:
        text = f"CAST({c} AS STRING)"
    return f"coalesce(concat('v', {text}), 'n')"


def by_place(schema: T.StructType) -> list[T.StructField]:
    return [T.StructField(f"c{i}", f.dataType) for i, f in enumerate(schema.fields)]


def canonical_rows(df: DataFrame, digits: int = 12, whole: int = 11) -> DataFrame:
    """The result with its cells as canonical texts, under names by place."""
    fields = by_place(df.schema)
    return df.toDF(*[f.name for f in fields]).selectExpr(*[f"{canonical(f, digits, whole)} AS {f.name}" for f in fields])


def fingerprint(df: DataFrame, mode: str = "bag") -> DataFrame:
    """One row (n, s, x) that equal results share, from one pass. ``set``
    ignores repeats, ``ordered`` adds each row's number to its hash."""
    rows = canonical_rows(df)
    cells = [F.lit(len(rows.columns)), *rows.columns]
    if mode == "set":
        rows = rows.distinct()
    if mode == "ordered":
        rows, cells = numbered(rows), [*cells, "place"]
    h, g = F.xxhash64(*cells), F.xxhash64(F.lit("x"), *cells)
    return rows.agg(F.count("*").alias("n"), F.coalesce(F.sum(h.cast("decimal(38,0)")), F.lit(0)).cast("decimal(38,0)").alias("s"), F.coalesce(F.bit_xor(g), F.lit(0)).alias("x"))


def fingerprint_sql(sql: str, schema: T.StructType) -> str:
    """The ``bag`` fingerprint of a query as one text: building it from columns
    takes some hundred calls to the JVM, far more time than a small query runs."""
    fields = by_place(schema)
    names = ", ".join(f.name for f in fields)
    rows = f"SELECT {', '.join(f'{canonical(f)} AS {f.name}' for f in fields)} FROM (\n{sql}\n) AS q({names})"
    cells = f"{len(fields)}, {names}"
    return f"SELECT count(*) AS n, CAST(coalesce(sum(CAST(xxhash64({cells}) AS DECIMAL(38, 0))), 0) AS DECIMAL(38, 0)) AS s, coalesce(bit_xor(xxhash64('x', {cells})), 0) AS x FROM ({rows})"


@dataclass
class Scan:
    """A query of one block without groups, orders, limits, subqueries and
    DISTINCT: what it reads, which rows it keeps and what it shows of them.
    ``calls`` are its aggregates (name, argument), empty where it lists rows; an item
    has the place of a call in braces."""

    source: str
    where: str
    calls: list[tuple[str, str]]
    items: list[str]


def scan_of(sql: str) -> Scan | None:
    tree = parse(sql)
    if tree.role != "query" or [k.role for k in tree.kids] != ["block"] or len(tree.find("query")) > 1 or len(tree.find("block")) > 1 or "{" in sql:
        return None
    parts = {k.role: k for k in tree.kids[0].kids}
    if not {"select", "from"} <= parts.keys() <= {"select", "from", "where"} or parts["select"].value:
        return None
    text = lambda n: sql[n.start : n.stop]
    calls, items, bare = [], [], False
    for item in parts["select"].kids:
        n, own = item.kids[0], []
        todo = [n]
        while todo:
            k = todo.pop()
            if k.role == "func" and k.value.upper() in TOTALS and len(k.kids) == 1:
                own.append(k)
                continue
            if k.role not in ("column", "literal", "op", "paren") and not (k.role == "func" and k.value.upper() == "ROUND"):
                return None
            bare |= k.role == "column"
            todo += k.kids
        shown, at = "", n.start
        for k in sorted(own, key=lambda k: k.start):
            if any(x.role not in ("column", "literal", "op", "paren", "star") for x in k.kids[0].walk()):
                return None
            shown += sql[at : k.start] + "{" + str(len(calls)) + "}"
            calls.append((k.value.upper(), "" if k.kids[0].role == "star" else text(k.kids[0])))
            at = k.stop
        items.append(shown + sql[at : n.stop])
    if calls and (bare or any("{" not in i for i in items)) or not calls and not bare:
        return None
    return Scan(text(parts["from"]), re.sub(r"^WHERE\b", "", text(parts["where"]), flags=re.I).strip() if "where" in parts else "TRUE", calls, items)


def shared_sql(scans: list[tuple[Scan, T.StructType]]) -> str:
    """One row with the ``bag`` fingerprints (n0, s0, x0, n1, ..) of queries that
    read one source: it is read and joined once, and each query's conditions
    filter its own aggregates."""
    rows, totals, out = [], [], []
    for i, (q, schema) in enumerate(scans):
        names = [f"q{i}c{j}" for j in range(len(q.items))]
        cells = ", ".join([str(len(names)), *[canonical(T.StructField(name, f.dataType)) for name, f in zip(names, schema.fields, strict=True)]])
        s, x = f"CAST(xxhash64({cells}) AS DECIMAL(38, 0))", f"xxhash64('x', {cells})"
        own = f"FILTER (WHERE q{i}w)"
        rows.append(f"({q.where}) AS q{i}w")
        if q.calls:
            rows += [f"{arg} AS q{i}a{k}" for k, (_, arg) in enumerate(q.calls) if arg]
            calls = [f"{name}({f'q{i}a{k}' if arg else '*'}) {own}" for k, (name, arg) in enumerate(q.calls)]
            totals += [f"{item.format(*calls)} AS {name}" for item, name in zip(q.items, names, strict=True)]
            out += [f"CAST(1 AS BIGINT) AS n{i}", f"CAST({s} AS DECIMAL(38, 0)) AS s{i}", f"{x} AS x{i}"]
        else:
            # cells of rows that are not kept are null, which costs no text
            rows += [f"CASE WHEN ({q.where}) THEN {item} END AS {name}" for item, name in zip(q.items, names, strict=True)]
            totals += [f"count(*) {own} AS n{i}", f"CAST(coalesce(sum({s}) {own}, 0) AS DECIMAL(38, 0)) AS s{i}", f"coalesce(bit_xor({x}) {own}, 0) AS x{i}"]
            out += [f"n{i}", f"s{i}", f"x{i}"]
    return f"SELECT {', '.join(out)} FROM (SELECT {', '.join(totals)} FROM (SELECT {', '.join(rows)} FROM {scans[0][0].source}))"


def numbered(rows: DataFrame) -> DataFrame:
    """``rows`` with their place in the result's order. Each partition counts
    its own rows; only one number a partition passes through a single task."""
    rows = rows.select("*", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)).alias("at")).persist(StorageLevel.DISK_ONLY)
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = rows.groupBy("part").agg(F.count("*").alias("rows")).withColumn("first", F.coalesce(F.sum("rows").over(before), F.lit(0)))
    return rows.join(F.broadcast(starts.select("part", "first")), "part").withColumn("place", F.col("first") + F.col("at")).drop("part", "at", "first")


class Runner:
    """Fingerprints of queries, each text once, several at a time. With
    ``plans``, texts of one optimized plan are run once as well: worth it where a
    run costs far more than an analysis. Queries that aggregate or list the rows of
    one source share its scan (``shared``, of which ``jobs`` counts). ``together`` of
    the others share a job, which pays on a small database, where starting one takes
    longer than its work."""

    def __init__(self, spark: SparkSession, threads: int = 8, mode: str = "bag", plans: bool = False, together: int = 1):
        self.spark, self.threads, self.mode, self.plans, self.known = spark, threads, mode, plans, {}
        self.together = together if mode == "bag" else 1
        self.runs, self.jobs, self.guard, self.begun = 0, 0, Lock(), {}

    def one(self, sql: str) -> tuple | None:
        """(n, s, x), or None if the query fails."""
        try:
            df = self.spark.sql(sql)
            if self.mode == "bag" and df.columns:
                return tuple(self.spark.sql(fingerprint_sql(self.quick(sql), df.schema)).collect()[0])
            return tuple(fingerprint(df, self.mode).first())
        except (PySparkException, Py4JJavaError):
            return None

    def quick(self, sql: str) -> str:
        """The text by which a query that analyses is run (``by_keys``), or its
        own where Spark does not take the other, as in a correlated subquery."""
        other = by_keys(sql, True)
        if other != sql:
            try:
                self.spark.sql(other).schema  # noqa: B018 - forces analysis
            except (PySparkException, Py4JJavaError):
                return sql
        return other

    def some(self, queries: list[str]) -> list[tuple | None]:
        """``one`` of each, by one job. If it fails, they are run one by one."""
        if len(queries) == 1:
            return [self.one(queries[0])]
        parts = {}
        for i, q in enumerate(queries):
            try:
                schema = self.spark.sql(q).schema
                parts[i] = f"SELECT {i} AS i, * FROM ({fingerprint_sql(self.quick(q), schema)})"
            except (PySparkException, Py4JJavaError):
                continue
        try:
            found = {r.i: (r.n, r.s, r.x) for r in self.spark.sql("\nUNION ALL\n".join(parts.values())).collect()} if parts else {}
        except (PySparkException, Py4JJavaError):
            return [self.one(q) for q in queries]
        return [found.get(i) for i in range(len(queries))]

    def shared(self, queries: list[str]) -> list[tuple | None]:
        """``one`` of each, of queries whose scans have one source (``scan_of``)."""
        parts = {}
        for i, q in enumerate(queries):
            try:
                parts[i] = scan_of(q), self.spark.sql(q).schema
            except (PySparkException, Py4JJavaError):
                continue
        try:
            row = self.spark.sql(shared_sql(list(parts.values()))).collect()[0] if parts else ()
        except (PySparkException, Py4JJavaError):
            return [self.one(q) for q in queries]
        self.jobs += bool(parts)
        found = {i: tuple(row[3 * k : 3 * k + 3]) for k, i in enumerate(parts)}
        return [found.get(i) for i in range(len(queries))]

    def all(self, queries: Iterable[str]) -> dict[str, tuple | None]:
        """What is known, ``queries`` included. A text that another thread has
        begun is waited for."""
        with self.guard:
            new = sorted({q for q in queries} - self.known.keys())
            others = {self.begun[q] for q in new if q in self.begun}
            new, own = [q for q in new if q not in self.begun], Future()
            self.begun |= dict.fromkeys(new, own)
        try:
            self.run_new(new)
            own.set_result(None)
        except BaseException as e:
            own.set_exception(e)
            raise
        finally:
            with self.guard:
                for q in new:
                    del self.begun[q]
        for other in others:
            other.result()
        return self.known

    def run_new(self, new: list[str]) -> None:
        with ThreadPoolExecutor(self.threads) as pool:
            keys = dict(zip(new, pool.map(lambda q: plan_key(self.spark, q) or q, new), strict=True)) if self.plans else {q: q for q in new}
            first = {key: q for q, key in reversed(keys.items())}
            texts = list(first.values())
            alike: dict[str, list[str]] = {}
            for q in texts:
                own = scan_of(q) if self.mode == "bag" else None
                alike.setdefault(own.source if own else "", []).append(q)
            rest = alike.pop("", []) + [q for own in alike.values() if len(own) == 1 for q in own]
            size = max(1, min(self.together, -(-len(rest) // self.threads)))
            chunks = [(self.shared, own[i : i + SCANS]) for own in alike.values() if len(own) > 1 for i in range(0, len(own), SCANS)]
            chunks += [(self.some, rest[i : i + size]) for i in range(0, len(rest), size)]
            parts = pool.map(lambda c: c[0](c[1]), chunks)
            known = {q: x for (_, own), part in zip(chunks, parts, strict=True) for q, x in zip(own, part, strict=True)}
            found = {key: known[q] for key, q in first.items()}
        with self.guard:
            self.runs += len(first)
            self.known |= {q: found[key] for q, key in keys.items()}

    def same(self, a: str, b: str) -> bool:
        self.all([a, b])
        return self.known[a] is not None and self.known[a] == self.known[b]


def same_result(spark: SparkSession, a: str, b: str, mode: str = "bag", strict: bool = True) -> bool:
    """Whether two queries return the same rows; a failing one equals nothing.
    ``strict`` confirms equal fingerprints by the cells themselves, doubles in the
    15 digits that they hold: 12 do not tell cents of large sums apart."""
    equal = Runner(spark, 2, mode).same(a, b)
    if equal and strict and mode != "ordered":
        x, y = (canonical_rows(spark.sql(q), 15, 15) for q in (a, b))
        x, y = (x.distinct(), y.distinct()) if mode == "set" else (x, y)
        return not x.exceptAll(y).limit(1).count() and not y.exceptAll(x).limit(1).count()
    return equal


def witness(spark: SparkSession, sf_dir: str, share: int = 10, tables: Iterable[str] = TABLES[:9]) -> SparkSession:
    """A session over a smaller database that keeps keys consistent: the orders
    and events of every ``share``-th customer by hash, what they refer to, and every
    ``share``-th part and supplier that they do not. A difference of two queries on it proves a difference of the queries; equality
    proves nothing."""
    db = open_db(spark, sf_dir, tables)
    drawn = lambda key: F.pmod(F.xxhash64(F.col(key).cast("long")), F.lit(share)) == 0
    kept = lambda name, key: db.table(name).where(drawn(key))
    orders, lines = kept("orders", "o_custkey"), db.table("lineitem")
    lines = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi")
    named = lambda name, key, by: kept(name, key).unionAll(db.table(name).where(~drawn(key)).join(lines, F.col(key) == F.col(by), "left_semi"))
    parts = {"orders": orders, "lineitem": lines, "events": kept("events", "user_id"), "customer": kept("customer", "c_custkey"), "part": named("part", "p_partkey", "l_partkey"), "supplier": named("supplier", "s_suppkey", "l_suppkey")}
    for name, df in parts.items():
        df.createOrReplaceTempView(name)
    return db


def written_witness(spark: SparkSession, sf_dir: str, limit: int = 4 << 20, tables: Iterable[str] = TABLES[:9]) -> SparkSession | None:
    """A session over a written witness of about ``limit`` bytes; None for a
    database that is no larger. Each table is one file, read into memory once, as
    thousands of queries read it."""
    size = sum(folder_bytes(spark, f"{sf_dir}/{t}.parquet") for t in tables)
    if size <= limit:
        return None
    db, folder = witness(spark, sf_dir, -(-size // limit), tables), workspace(spark, "witness")
    with ThreadPoolExecutor(4) as pool:
        list(pool.map(lambda t: (db.table(t).repartition(1) if t in DRAWN else db.table(t)).write.parquet(f"{folder}/{t}.parquet"), tables))
    small = open_db(spark, folder, tables)
    for t in tables:
        small.catalog.cacheTable(t)
    return small
