"""The question-schema structure: tables, columns, keys, foreign keys and small
value dictionaries of a database, and the links from a question's phrases.

Links come from names, abbreviations in names, values, evidence given with the
question, and words learned from the train split; an external linker can add
its own. The catalog's size follows the schema, not the rows."""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from functools import cached_property, lru_cache, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

WHOLE = ("int", "bigint", "smallint", "tinyint")
Link = tuple[str, str, str, str, float]  # phrase, table, column or "", relation, weight


@dataclass
class Catalog:
    columns: dict[str, dict[str, str]]
    keys: dict[str, str] = field(default_factory=dict)
    foreign: list[tuple[str, str, str, str]] = field(default_factory=list)  # table, column, table, column
    values: dict[str, list[str]] = field(default_factory=dict)
    #: word -> (table, column, value or "") that it stands for, learned
    words: dict[str, tuple[str, str, str]] = field(default_factory=dict)

    @cached_property
    def names(self) -> Names:
        """What single words can link to; columns and values stay as they are."""
        return Names(self.columns, self.values)

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "names"}

    def owners(self, column: str) -> list[str]:
        return [t for t, cols in self.columns.items() if column.lower() in cols]

    def edge(self, a: str, b: str) -> tuple[str, str] | None:
        """The columns of the one foreign key between two tables."""
        found = [(c, d) if t == a else (d, c) for t, c, u, d in self.foreign if {t, u} == {a, b}]
        return found[0] if len(found) == 1 else None

    def keeps_rows(self, a: str, b: str) -> bool:
        """Whether an inner join of ``a`` with ``b`` along their foreign key
        returns each row of ``a`` once: b is the side with the unique key, and
        no value of a is missing there."""
        return any((t, u) == (a, b) for t, _, u, _ in self.foreign) and self.edge(a, b) is not None

    def path(self, a: str, b: str) -> list[tuple[str, str, str, str]]:
        """Foreign keys of a shortest way between two tables; empty if none."""
        ways: dict[str, list] = {a: []}
        todo = [a]
        for t in todo:
            for e in self.foreign:
                for u, v in ((e[0], e[2]), (e[2], e[0])):
                    if u == t and v not in ways:
                        ways[v] = [*ways[t], e]
                        todo.append(v)
        return ways.get(b, [])


def stem(column: str) -> str:
    return column.split("_", 1)[-1]


def union(frames: Iterable[DataFrame]) -> DataFrame | None:
    frames = list(frames)
    return reduce(DataFrame.unionAll, frames) if frames else None


def infer_keys(spark: SparkSession, tables: list[str]) -> DataFrame:
    """(tab, col): columns named like keys whose values are unique and not null.
    One approximate aggregate over each table, one job for all; then one exact
    aggregate for the columns that are left."""
    named = {t: [c for c in spark.table(t).columns if re.search(r"(key|_id)$", c)] for t in tables}
    rough = union(
        spark.table(t).agg(F.count("*").alias("n"), *[F.approx_count_distinct(c, 0.02).alias(c) for c in cols])
        .select(F.lit(t).alias("tab"), F.explode(F.array(*[F.struct(F.lit(c).alias("col"), F.col("n"), F.col(c).alias("d")) for c in cols])).alias("r")).select("tab", "r.*")
        for t, cols in named.items() if cols
    )
    left = [(r.tab, r.col) for r in rough.where("n > 0 and d >= 0.9 * n").collect()] if rough is not None else []
    exact = union(
        spark.table(t).agg(F.count("*").alias("n"), F.count_distinct(c).alias("d"), F.count(c).alias("full")).select(F.lit(t).alias("tab"), F.lit(c).alias("col"), "n", "d", "full")
        for t, c in left
    )
    unique = {(r.tab, r.col) for r in exact.where("n = d and n = full").collect()} if exact is not None else set()
    order = [(t, c) for t in tables for c in named[t] if (t, c) in unique]
    return spark.createDataFrame(order, "tab string, col string")


def infer_foreign_keys(spark: SparkSession, tables: list[str], keys: dict[str, str]) -> DataFrame:
    """(tab, col, ref_tab, ref_col, orphans): columns with the stem of a unique
    key of another table and no value outside it. Inclusion alone would invent
    keys, as all integer keys start at 0. Least and greatest values rule most
    pairs out in one job; the rest are tested exactly in one more."""
    kinds = {t: dict(spark.table(t).dtypes) for t in {*tables, *keys}}
    pairs = [(t, c, u, k) for t in tables for c, kind in kinds[t].items() for u, k in keys.items() if u != t and stem(c) == stem(k) != "id" and c != keys.get(t) and kind in WHOLE]
    if not pairs:
        return spark.createDataFrame([], "tab string, col string, ref_tab string, ref_col string, orphans long")
    ends = defaultdict(set)
    for t, c, u, k in pairs:
        ends[t].add(c)
        ends[u].add(k)
    spans = union(
        spark.table(t).agg(*[F.struct(F.min(c).cast("long"), F.max(c).cast("long")).alias(c) for c in sorted(cols)])
        .select(F.explode(F.map_from_arrays(F.array(*[F.lit(f"{t}.{c}") for c in sorted(cols)]), F.array(*sorted(cols)))).alias("name", "span")).select("name", "span.*")
        for t, cols in ends.items()
    )
    span = {r[0]: (r[1], r[2]) for r in spans.collect()}
    inside = lambda a, b: None in (*a, *b) or b[0] <= a[0] and a[1] <= b[1]
    likely = [p for p in pairs if inside(span[f"{p[0]}.{p[1]}"], span[f"{p[2]}.{p[3]}"])]
    tests = union(
        spark.table(t).where(F.col(c).isNotNull()).select(F.col(c).alias("v")).join(spark.table(u).select(F.col(k).alias("v")), "v", "left_anti")
        .agg(F.count("*").alias("orphans")).select(F.lit(i).alias("i"), "orphans")
        for i, (t, c, u, k) in enumerate(likely)
    )
    found = {r.i: r.orphans for r in tests.collect()} if tests is not None else {}
    rows = [(*p, found[i]) for i, p in enumerate(likely) if not found[i]]
    return spark.createDataFrame(rows, "tab string, col string, ref_tab string, ref_col string, orphans long")


def build_catalog(spark: SparkSession, tables: list[str], most_values: int = 60) -> Catalog:
    """``most_values``: columns with more distinct texts have no dictionary."""
    columns = {t: {c.lower(): k for c, k in spark.table(t).dtypes} for t in tables}
    with ThreadPoolExecutor(1) as pool:
        values = pool.submit(dictionaries, spark, columns, most_values)
        keys: dict[str, str] = {}
        for r in infer_keys(spark, tables).collect():
            keys.setdefault(r.tab, r.col)  # the first column of a table that is unique
        foreign = [(r.tab, r.col, r.ref_tab, r.ref_col) for r in infer_foreign_keys(spark, tables, keys).collect()]
        return Catalog(columns, keys, foreign, values.result())


def dictionaries(spark: SparkSession, columns: dict[str, dict[str, str]], most_values: int) -> dict[str, list[str]]:
    """The values of text columns with at most ``most_values`` distinct ones."""
    text = {t: [c for c, k in cols.items() if k == "string" and c not in ("text", "html", "props", "url")] for t, cols in columns.items()}
    named = lambda make: union(
        spark.table(t).agg(*[make(c).alias(c) for c in cols]).select(F.explode(F.array(*[F.struct(F.lit(c).alias("col"), F.col(c).alias("v")) for c in cols])).alias("r")).select("r.*")
        for t, cols in text.items() if cols
    )
    counts = named(F.approx_count_distinct)
    few = {r.col for r in counts.where(F.col("v") <= most_values).collect()} if counts is not None else set()
    text = {t: [c for c in cols if c in few] for t, cols in text.items()}
    sets = named(lambda c: F.sort_array(F.collect_set(c)))
    return {r.col: list(r.v) for r in sets.collect()} if sets is not None else {}


@lru_cache(8)
def catalog_of(spark: SparkSession, sf_dir: str) -> Catalog:
    """The catalog of a database folder, made once, with the words of the train
    split of the question bank."""
    from .bank import train_questions
    from .execution import TABLES, open_db

    catalog = build_catalog(open_db(spark, sf_dir, TABLES[:8]), TABLES[:8])
    catalog.words = learn_words([(q.text, q.gold) for q in train_questions()], catalog)
    return catalog


# ---------------------------------------------------------------- the graph


def schema_nodes(spark: SparkSession, catalog: Catalog) -> DataFrame:
    rows = [("table", t, None, None, t in catalog.keys) for t in catalog.columns]
    rows += [("column", t, c, k, catalog.keys.get(t) == c) for t, cols in catalog.columns.items() for c, k in cols.items()]
    return spark.createDataFrame(rows, "kind string, tab string, col string, dtype string, is_key boolean")


def edge_rows(catalog: Catalog) -> list[tuple[str, str, str]]:
    """(src, dst, rel): columns of tables, of one table, keys and foreign keys."""
    rows = [(t, f"{t}.{c}", "has_column") for t, cols in catalog.columns.items() for c in cols]
    rows += [(f"{t}.{c}", f"{t}.{d}", "same_table") for t, cols in catalog.columns.items() for c, d in zip(cols, list(cols)[1:])]
    rows += [(f"{t}.{c}", t, "pk") for t, c in catalog.keys.items()]
    return rows + [(f"{t}.{c}", f"{u}.{d}", "fk") for t, c, u, d in catalog.foreign]


def schema_edges(spark: SparkSession, catalog: Catalog) -> DataFrame:
    return spark.createDataFrame(edge_rows(catalog), "src string, dst string, rel string")


# ---------------------------------------------------------------- phrases and links


def lemma(word: str) -> str:
    w = word.lower()
    if len(w) > 4 and w.endswith("ies"):
        return w[:-3] + "y"
    return w[:-1] if len(w) > 3 and w.endswith("s") and not w.endswith(("ss", "us")) else w


def question_words(question: str) -> list[str]:
    return re.findall(r"[A-Za-z0-9_#-]+", question or "")


def phrases(question: str, longest: int = 3) -> list[tuple[int, str]]:
    """(first word's place, phrase) of all runs of 1 to ``longest`` words."""
    words = question_words(question)
    return [(i, " ".join(words[i : i + n])) for n in range(1, longest + 1) for i in range(len(words) - n + 1)]


def piece_of(name: str, word: str) -> str:
    """The part of a column's name that a word stands for: the word itself, or
    its beginning of three letters or more at an end of the name."""
    if len(word) >= 3 and word in name:
        return word
    for size in range(min(len(word), len(name)), 2, -1):
        if len(word) >= 5 and (name.endswith(word[:size]) or name.startswith(word[:size])):
            return word[:size]
    return ""


def uncovered(name: str, word: str) -> str | None:
    """A name without the letters that a word covers; None if it covers none."""
    w = word.lower()
    piece = piece_of(name, lemma(w)) or piece_of(name, w)
    return name.replace(piece, "", 1) if piece else None


def name_link(name: str, phrase: str) -> float:
    """Share of a name's letters that a phrase's words cover; 0 if one of the
    words covers none."""
    left: str | None = name
    for w in phrase.split():
        left = uncovered(left, w)
        if left is None:
            return 0.0
    return 1 - len(left) / len(name)


class Names:
    """Tables, names of columns and values by the word that they are linked
    from. A phrase covers letters of a name only if its first word does, so most
    words of a text are done with one look-up; each is compared with the schema
    once (the most recent ones are kept)."""

    def __init__(self, columns: dict[str, dict[str, str]], values: dict[str, list[str]]):
        self.tables = [(t, lemma(t)) for t in columns]
        self.stems: dict[str, list[tuple[str, str]]] = defaultdict(list)
        self.exact: dict[str, list[Link]] = defaultdict(list)
        self.lemmas: dict[str, list[Link]] = defaultdict(list)
        self.sole: dict[str, list[Link]] = defaultdict(list)
        for t, cols in columns.items():
            for c in cols:
                self.stems[stem(c)].append((t, c))
                known = values.get(c, [])
                # a value of one word and signs or digits; the word must tell it apart
                parts = {v: "".join(re.findall(r"[A-Za-z]+", v)).lower() for v in known if re.fullmatch(r"[^A-Za-z]*[A-Za-z]{3,}[^A-Za-z]*", v)}
                often = Counter(parts.values())
                for v in known:
                    link = (v, t, c, "link_value", 1.0)
                    self.exact[v].append(link)
                    if len(v) > 1:
                        self.lemmas[lemma(v)].append(link)
                    if v in parts and often[parts[v]] == 1:
                        self.sole[parts[v]].append(link)
        # what a word covers of a name holds the word's first three letters
        self.holding: dict[str, dict[str, None]] = defaultdict(dict)
        for name in self.stems:
            for i in range(len(name) - 2):
                self.holding[name[i : i + 3]][name] = None
        self.of = lru_cache(1 << 16)(self._of)

    def _of(self, word: str) -> tuple[list[tuple[str, str, float]], list[tuple[str, str]], list[Link]]:
        """(table, relation, weight) of a word, (name, what the word leaves of
        it) and its values."""
        w = lemma(word)
        tables = [(t, "link_exact", 1.0) for t, own in self.tables if w == own]
        tables += [(t, "link_partial", 0.6) for t, own in self.tables if len(word) >= 4 and t.startswith(w) and w != own]
        near = self.holding.get(w[:3], {}) | self.holding.get(word[:3].lower(), {})
        begun = [(name, left) for name in near for left in [uncovered(name, word)] if left is not None]
        return tables, begun, [link for by, key in ((self.exact, word), (self.lemmas, w), (self.sole, word.lower())) for link in by.get(key, ())]

    def columns_of(self, words: list[str], longest: int = 3) -> list[tuple[str, str, float]]:
        """(phrase, name, share of its letters) of the phrases that cover some
        of a name, shorter phrases first, then by place."""
        out, seen = [], set()
        for i, word in enumerate(words):
            for name, left in self.of(word)[1]:
                for n in range(1, min(longest, len(words) - i) + 1):
                    left = left if n == 1 else uncovered(left, words[i + n - 1])
                    if left is None:
                        break
                    phrase = " ".join(words[i : i + n])
                    if (phrase, name) not in seen:
                        seen.add((phrase, name))
                        out.append((n, i, phrase, name, 1 - len(left) / len(name)))
        return [x[2:] for x in sorted(out, key=lambda x: x[:2])]


def evidence_links(evidence: str, catalog: Catalog) -> list[Link]:
    """Links that a note states: ``word means column = 'value'``, or ``word
    means column`` or a table."""
    out: list[Link] = []
    for word, what, value in re.findall(r"([\w-]+) means (\w+)(?: = '([^']*)')?", evidence or ""):
        for t, cols in catalog.columns.items():
            if what == t:
                out.append((word, t, "", "link_synonym", 1.0))
            elif what in cols:
                out.append((value, t, what, "link_value", 1.0) if value else (word, t, what, "link_synonym", 1.0))
    return out


def question_links(question: str, catalog: Catalog, full: bool = False, evidence: str = "", external: Callable[[str, Catalog], Iterable[Link]] | None = None) -> list[Link]:
    """(phrase, table, column or "", relation, weight). Relations: link_exact,
    link_partial, link_synonym, link_value; ``full`` links all with all.
    ``external`` is another linker, whose links are added."""
    words = question_words(question)
    if full:
        targets = [(t, c) for t, cols in catalog.columns.items() for c in ("", *cols)]
        return sorted((w, t, c, "link_full", 0.1) for w in set(words) for t, c in targets)
    best: dict[tuple[str, str], Link] = {}

    def add(phrase: str, t: str, c: str, rel: str, weight: float) -> None:
        old = best.get((t, c))
        if old is None or weight > old[4]:
            best[t, c] = (phrase, t, c, rel, weight)

    values: list[Link] = []
    names = catalog.names
    for w in dict.fromkeys(words):
        tables, _, known = names.of(w)
        values += known
        for t, rel, weight in tables:
            add(w, t, "", rel, weight)
    for p, name, score in names.columns_of(words):
        if score >= 0.4:
            for t, c in names.stems[name]:
                add(p, t, c, "link_exact" if score == 1 else "link_partial", round(score, 3))
    for w in dict.fromkeys(words):
        if lemma(w) in catalog.words:
            t, c, v = catalog.words[lemma(w)]
            if v:
                values.append((v, t, c, "link_value", 1.0))
            else:
                add(w, t, c, "link_synonym", 0.9)
    for p, t, c, rel, weight in [*evidence_links(evidence, catalog), *(external(question, catalog) if external else [])]:
        if rel == "link_value":
            values.append((p, t, c, rel, weight))
        else:
            add(p, t, c, rel, weight)
    return sorted({*best.values(), *values})


def learn_words(pairs: list[tuple[str, str]], catalog: Catalog, support: int = 3, share: float = 0.9) -> dict[str, tuple[str, str, str]]:
    """Words of questions that stand for a value or a table of their right query
    without naming it: seen in ``support`` questions, with it in ``share`` of
    them, and the other way round. A word that is part of a column's name stands
    for no table. Only the train split is read."""
    from .sqltree import parse

    together, seen, given = Counter(), Counter(), Counter()
    bare = Catalog(catalog.columns, catalog.keys, catalog.foreign, catalog.values)
    for text, gold in pairs:
        tree = parse(gold)
        links = question_links(text, bare)
        linked = {lemma(x) for p, *_, weight in links if weight == 1 for x in p.split()}
        parts = {lemma(x) for p, _, c, *_ in links if c for x in p.split()}
        things = {(r.value.lower(), "", "") for r in tree.find("relation")}
        for op in tree.find("op"):
            if op.value == "=" and op.kids[0].role == "column" and op.kids[1].role == "literal" and op.kids[1].value.startswith("'"):
                c = op.kids[0].value.split(".")[-1].lower()
                things |= {(t, c, op.kids[1].value.strip("'")) for t in catalog.owners(c)}
        words = {lemma(w) for w in question_words(text) if len(w) > 3 and w.islower()} - linked
        seen.update(words)
        given.update(things)
        together.update((w, x) for w in words for x in things if x[2] or w not in parts)
    out: dict[str, tuple[str, str, str]] = {}
    total = len(pairs)
    for w, n in seen.items():
        # what comes with the word far more often than without it
        fits = [(together[w, x] / n - given[x] / total, x) for x in given if n >= support and together[w, x] >= share * n and given[x] < 0.3 * total and together[w, x] >= share * given[x]]
        if fits:
            best = max(fits, key=lambda f: (f[0], f[1][2] != "", f[1]))
            if sum(f[0] >= best[0] - 1e-9 for f in fits) == 1:
                out[w] = best[1]
    return out


# ---------------------------------------------------------------- assembly


def structure(question: str, catalog: Catalog, **options) -> list[tuple[str, str, str, float]]:
    """(src, dst, rel, weight): the schema's edges and the question's links."""
    rows = [(*e, 1.0) for e in edge_rows(catalog)]
    return rows + [(f"q:{p}", f"{t}.{c}" if c else t, rel, w) for p, t, c, rel, w in question_links(question, catalog, **options)]


def near_tables(catalog: Catalog, tables: Iterable[str], links: Iterable[Link] = ()) -> set[str]:
    """Tables of the query, those linked, and those on ways between them."""
    out = {t for t in tables if t in catalog.columns} | {t for _, t, c, _, _ in links if not c}
    for a in list(out):
        for b in list(out):
            out |= {x for e in catalog.path(a, b) for x in (e[0], e[2])}
    return out


def linear_structure(catalog: Catalog, tables: Iterable[str], links: Iterable[Link]) -> str:
    """The part of the structure near a query, as text: tables with the columns
    that are linked or keys, foreign keys, then links."""
    links = list(links)
    near = near_tables(catalog, tables, links)
    linked = {(t, c) for _, t, c, _, _ in links}
    parts = []
    for t in sorted(near):
        cols = [c for c in catalog.columns[t] if (t, c) in linked or catalog.keys.get(t) == c or any((t, c) in ((e[0], e[1]), (e[2], e[3])) for e in catalog.foreign)]
        parts.append(f"{t}({', '.join(cols)})")
    parts += [f"{t}.{c}={u}.{d}" for t, c, u, d in catalog.foreign if t in near and u in near]
    return " | ".join(parts + [f"{p} -> {t + '.' + c if c else t} [{rel[5:]}]" for p, t, c, rel, _ in links if t in near])


def structure_frame(questions: DataFrame, catalog: Catalog) -> DataFrame:
    """(question_id, src, dst, rel, weight) of the links of many questions; the
    catalog is broadcast, whose size is that of the schema."""
    import pandas as pd

    shared = questions.sparkSession.sparkContext.broadcast(catalog)

    def run(frames):
        for frame in frames:
            rows = [(i, f"q:{p}", f"{t}.{c}" if c else t, rel, w) for i, q in zip(frame["question_id"], frame["question"], strict=True) for p, t, c, rel, w in question_links(q or "", shared.value)]
            yield pd.DataFrame(rows, columns=["question_id", "src", "dst", "rel", "weight"])

    return questions.select("question_id", "question").mapInPandas(run, "question_id string, src string, dst string, rel string, weight double")
