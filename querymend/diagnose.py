"""What a query does about its question, and the edits that would mend it.

``View`` compares tree, catalog and links: which tables, columns, values and
numbers are asked for, which are used, and where. From it come

* ``observations``: words that describe the comparison, the model's input;
* ``findings``: violations with the edit that removes each. A finding is a proof
  if the schema alone decides (the static rules, each the inverse of an
  operator of ``perturb``); other findings localise what the model detects.

No data and no gold query is read."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterable
from dataclasses import dataclass

from .catalog import Catalog, Link, lemma, near_tables, piece_of, question_links, question_words, stem
from .perturb import column_of
from .sqltree import AGGREGATES, Node, minimal_subtree, parse, render

#: Words of a question that ask for a function, and for an order.
FUNCTION_CUES = {"average": "AVG", "total": "SUM", "sum": "SUM", "largest": "MAX", "maximum": "MAX", "smallest": "MIN", "minimum": "MIN", "many": "COUNT", "number": "COUNT", "count": "COUNT"}
ORDER_CUES = {"highest": "DESC", "largest": "DESC", "most": "DESC", "lowest": "", "smallest": "", "least": "", "fewest": ""}
COMPARE_CUES = {("at", "least"): ">=", ("at", "most"): "<=", ("above",): ">", ("below",): "<", ("more", "than"): ">", ("less", "than"): "<"}
NUMBERS = {w: str(i) for i, w in enumerate("one two three four five six seven eight nine ten".split(), 1)}
DENIALS = {"never", "without", "not"}
HEADS = {"list", "show", "give", "return"}


@dataclass
class Finding:
    slot: int
    proof: bool
    reason: str
    slots: dict[str, str]
    nodes: list[Node]
    fix: Callable[[], object]
    #: table.column elements of the schema that it involves
    elements: tuple[str, ...] = ()


def lit(text: str) -> Node:
    return Node("literal", f"'{text}'")


class Case:
    """One question with one query, taken apart."""

    def __init__(self, question: str, sql: str, catalog: Catalog, linking: str = "links", evidence: str = "", links: Iterable[Link] | None = None):
        self.question, self.catalog, self.tree = question or "", catalog, parse(sql or "")
        self.links = list(links) if links is not None else question_links(self.question, catalog, linking == "full", evidence) if linking != "none" else []
        self.words = [w.lower() for w in question_words(self.question)]
        blocks = self.tree.find("block")
        self.block = blocks[0] if blocks else None
        self.inner = {id(x) for b in blocks[1:] for x in b.walk()}
        self.relations = self.tree.find("relation")
        self.read = [r.value.lower() for r in self.relations]
        self.outer = [r.value.lower() for r in self.relations if id(r) not in self.inner]
        self.flat = not self.tree.find("derived") and not self.tree.find("cte") and not self.tree.find("setop")
        self.asked = self._asked()
        self.wanted = self._wanted()

    def place(self, phrase: str) -> int:
        first = phrase.lower().split()
        return next((i for i in range(len(self.words)) if self.words[i : i + len(first)] == first), len(self.words))

    def numbered(self, phrase: str) -> bool:
        """Whether a number follows, as in ``nation 3``: a key, not a table."""
        at = self.place(phrase) + len(phrase.split())
        return at < len(self.words) and self.words[at].isdigit()

    def _asked(self) -> list[str]:
        """Tables that the question names, in its order, then those that alone
        hold a value of it; if there are none, those of columns that only one
        table has."""
        named = sorted((self.place(p), t) for p, t, c, rel, _ in self.links if not c and rel != "link_full" and not (self.numbered(p) and any(f"{lemma(p)}key" in map(stem, cols) for u, cols in self.catalog.columns.items() if u != t)))
        out = list(dict.fromkeys(t for _, t in named))
        for links in self.values_by_word().values():
            owners = {t for _, t, _ in links}
            if len(owners) == 1 and not owners & set(out):
                out += sorted(owners)
        if not out:
            columns = [x for x in self.links if x[2] and x[3] not in ("link_value", "link_full")]
            best = {}
            for p, t, c, _, weight in columns:
                best.setdefault(p, {}).setdefault(t, weight)
            sole = [(-max(ts.values()), next(iter(ts))) for p, ts in best.items() if len(ts) == 1]
            out = list(dict.fromkeys(t for _, t in sorted(sole)))[:1]
        return out

    def values_by_word(self) -> dict[str, list[tuple[str, str, str]]]:
        """(value, table, column) of the value links, by the letters of the
        value: links that share them are readings of one word."""
        out: dict[str, list] = {}
        for p, t, c, rel, _ in self.links:
            if rel == "link_value":
                out.setdefault(re.sub(r"[^a-z]+", " ", p.lower()).strip() or p, []).append((p, t, c))
        return out

    def _wanted(self) -> list[tuple[str, str, str, float]]:
        """(phrase, table, column, weight) of the columns asked for: exact names
        first; words of a table's name or of a better link do not count again.
        Of equal links that of the next table that is named counts."""
        scope = near_tables(self.catalog, self.asked) | set(self.read)
        tables = {w for p, t, c, rel, _ in self.links if not c and t in self.asked for w in p.lower().split()}
        ahead = {t: self.place(p) for p, t, c, _, _ in self.links if not c}
        out, taken = [], set(tables)

        def rank(link: Link) -> tuple:
            p, t, _, _, weight = link
            gap = ahead.get(t, 99) - self.place(p)
            return (-weight, -len(p.split()), t not in self.asked, gap if gap > 0 else 50 - gap, t)

        for p, t, c, rel, weight in sorted((x for x in self.links if x[2] and x[1] in scope and x[3] not in ("link_value", "link_full")), key=rank):
            words = set(p.lower().split())
            if not words & taken and not any(cue in words for cue in ("total",) if len(words) == 1):
                out.append((p, t, c, weight))
                taken |= words
        return out

    def columns(self, role: str) -> list[Node]:
        """Columns of a clause of the outer query."""
        at = self.tree.kid(role) if role in ("order", "limit") else self.block.kid(role) if self.block else None
        return [n for n in at.find("column") if id(n) not in self.inner] if at else []

    def used(self, joins: bool = False) -> list[Node]:
        """Columns outside of join conditions (and of the inner queries)."""
        on = {id(x) for o in self.tree.find("on") for x in o.walk()}
        return [c for c in self.tree.find("column") if id(c) not in self.inner and (joins or id(c) not in on)]

    def owner(self, column: str) -> str | None:
        return next((t for t in self.read if column in self.catalog.columns.get(t, {})), None)

    def functions(self) -> list[Node]:
        return [f for f in self.tree.find("func") if id(f) not in self.inner and f.value.split()[0].upper() in AGGREGATES]

    def comparisons(self) -> list[Node]:
        return [op for op in self.tree.find("op") if len(op.kids) == 2 and op.kids[0].role == "column" and op.kids[1].role == "literal"]

    def numbers(self) -> list[str]:
        return [NUMBERS.get(w, w) for w in self.words if w.isdigit() or w in NUMBERS]

    def asked_values(self) -> list[tuple[str, str, str]]:
        """(value, table, column) of each word that stands for a value: of its
        readings those of a table that is named, or else read, or else all."""
        out = []
        for links in self.values_by_word().values():
            out += [v for v in links if v[1] in self.asked] or [v for v in links if v[1] in self.read] or links
        return out

    def add_condition(self, node: Node) -> None:
        where = self.block.kid("where")
        if where is None:
            at = next((i for i, k in enumerate(self.block.kids) if k.role in ("group", "having")), len(self.block.kids))
            self.block.kids.insert(at, Node("where", "", [node]))
        elif where.kids[0].role == "bool" and where.kids[0].value == "AND":
            where.kids[0].kids.append(node)
        elif where.kids[0].role == "bool":
            where.kids = [Node("bool", "AND", [Node("paren", "", [where.kids[0]]), node])]
        else:
            where.kids = [Node("bool", "AND", [where.kids[0], node])]

    def add_table(self, t: str) -> bool:
        """Joins ``t`` along foreign keys, with what lies on the way."""
        source = self.block.kid("from")
        for have in self.outer:
            way = self.catalog.path(have, t)
            if way:
                seen = [have]
                for a, c, b, d in way:
                    new, left, right = (b, c, d) if a in seen else (a, d, c)
                    if new not in self.outer:
                        on = Node("on", "", [Node("op", "=", [Node("column", left), Node("column", right)])])
                        source.kids[0] = Node("join", "", [source.kids[0], Node("relation", new), on])
                        self.outer.append(new)
                    seen.append(new)
                return True
        return False


# ---------------------------------------------------------------- observations

#: What a token says, in words: these come with it in the model's input.
SAYS = {
    "tab-": "missing table", "tab+": "extra redundant unnecessary columns", "tab~": "wrong table", "join~": "wrong join key", "col-": "missing column", "col+": "redundant column",
    "col~": "wrong column", "val~": "value mismatch", "val-": "missing condition", "num+": "wrong condition", "num-": "missing condition", "cond~": "wrong condition",
    "fn~": "wrong function", "ord~": "wrong clause", "grp~": "wrong clause", "in~": "wrong subquery", "cmp~": "wrong operator", "ok": "correct sql",
}


def observations(case: Case) -> list[str]:
    """Tokens of the comparison. Those that state a difference come with the
    words of ``SAYS``; the others pair what is asked with what is used."""
    c, cat = case, case.catalog
    if c.block is None:
        return ["fb:syntax", "wrong", "clause"]
    out: list[str] = []

    def say(key: str, detail: str = "") -> None:
        out.extend([f"{key}{detail}", *SAYS.get(key, "").split()])

    near = near_tables(cat, c.asked)
    for t in c.asked:
        if t not in c.read:
            say("tab-", ":bridged" if any(cat.path(r, t) for r in c.read) and len(c.asked) > 1 else ":alone")
    for i, t in enumerate(c.read):
        if t not in cat.columns:
            say("tab~", ":unknown")
        elif t not in c.asked:
            busy = any(column_of(n) in cat.columns[t] for n in c.used())
            way = t in near
            kept = any(cat.keeps_rows(o, t) for o in c.read if o != t)
            if not way and c.flat and kept and not busy:
                out.append("tab=:kept")
            elif not way and c.flat:
                say("tab+" if i else "tab~", f":{'busy' if busy else 'idle'}:{'kept' if kept else 'grows'}")
    for on in c.tree.find("on"):
        op = on.kids[0]
        if op.role == "op" and op.value == "=" and all(k.role == "column" for k in op.kids):
            names = {column_of(k) for k in op.kids}
            fk = any(names == {e[1], e[3]} for e in cat.foreign)
            out.append("join=fk") if fk else say("join~")
    clause_of = {id(n): role for role in ("select", "where", "group", "having", "order") for n in c.columns(role)}
    used = {column_of(n) for n in c.tree.find("column")}
    wanted = {col for _, _, col, _ in c.wanted}
    value_columns = {col for _, _, col in c.asked_values()}
    for _, t, col, weight in c.wanted:
        if col in used:
            out.append(f"col=:{'full' if weight == 1 else 'part'}")
        elif t in c.read:
            say("col-" if col not in value_columns else "val-", ":full" if weight == 1 else ":part")
    for n in c.used():
        name, role = column_of(n), clause_of.get(id(n), "other")
        if c.owner(name) is None and name in {x for cols in cat.columns.values() for x in cols}:
            say("tab-", ":unresolved")
        elif name not in wanted and name not in value_columns and role != "order":
            key = name in cat.keys.values()
            twin = any(stem(name) != stem(w) and cat.columns.get(t, {}).get(name) == cat.columns.get(t, {}).get(w) and w not in used for _, t, w, _ in c.wanted)
            say("col~" if twin else "col+", f":{role}:{'key' if key else 'plain'}") if name not in c.words else out.append("col=:alias")
    literals = {n.value.strip("'") for n in c.tree.find("literal") if n.value.startswith("'")}
    asked = c.asked_values()
    for v, _, col in asked:
        if v in literals:
            out.append("val=")
        elif any(column_of(op.kids[0]) == col for op in c.comparisons()):
            say("val~", ":other")
        elif not any(w in literals for w, t, k in asked if w == v):
            say("val-")
    for v in literals - {v for v, _, _ in asked}:
        known = [x for op in c.comparisons() if op.kids[1].value == f"'{v}'" for x in cat.values.get(column_of(op.kids[0]), [])]
        say("val~" if v not in known else "cond~", ":case" if v.lower() in {x.lower() for x in known} and v not in known else ":extra" if v in known else ":unknown")
    numbers = [n.value for n in c.tree.find("literal") if not n.value.startswith("'")]
    own = c.numbers()
    for n in own:
        out.append("num=") if n in numbers else say("num-")
    scale = {n.value for n in c.tree.find("literal") for f in c.tree.find("func") if f.value.upper() == "ROUND" and any(n is k for k in f.kids[1:])}
    for n in numbers:
        if n not in own and n not in scale and n not in ("1", "0"):
            say("num+", ":limit" if c.tree.kid("limit") and c.tree.kid("limit").kids[0].value == n else "")
    linked = {w for p, *_ in c.wanted for w in p.lower().split()} | {lemma(t) for t in cat.columns}
    plain = [w for w in c.words if w not in linked and lemma(w) not in linked and w.isalpha() and w not in cat.words]
    cues = [f for w, f in FUNCTION_CUES.items() if w in plain]
    fns = sorted({f.value.split()[0].upper() for f in c.functions()})
    out += [f"fn:{f or 'none'}|{cue}" for f in fns or [""] for cue in cues or ["none"]]
    if cues and fns and not set(cues) & set(fns):
        say("fn~", f":{fns[0]}")
    order, limit, group = c.tree.kid("order"), c.tree.kid("limit"), c.block.kid("group")
    way = [ORDER_CUES[w] or "ASC" for w in plain if w in ORDER_CUES]
    now = (order.kids[0].value or "ASC") if order else "none"
    if way or order:
        top = any(w in ("highest", "lowest", "most", "fewest") for w in plain)
        out.append(f"ord:{now}|{way[0] if way else 'none'}|{'limit' if limit else 'all'}|{'top' if top else 'no'}")
        if way and top and (now != way[0] or not limit):
            say("ord~")
    per = any(w in ("per", "each", "by") for w in plain)
    out.append(f"grp:{'yes' if group else 'no'}|{'per' if per else 'no'}|{'having' if c.block.kid('having') else 'all'}|{'than' if 'than' in plain else 'no'}")
    mixed = bool(c.functions()) and any(i.kids[0].role == "column" for i in c.block.kid("select").kids)
    keys = {render(k).lower() for k in group.kids} if group else set()
    if mixed and any(i.kids[0].role == "column" and i.kids[0].value.lower() not in keys for i in c.block.kid("select").kids):
        say("grp~", ":ungrouped")
    if per and not group:
        say("grp~", ":lost")
    links = sorted({b.value for b in c.tree.find("bool") if id(b) not in c.inner})
    either = "or" in c.words
    out.append(f"bool:{'+'.join(links) or 'none'}|{'or' if either else 'no'}")
    if "AND" in links and either or "OR" in links and not either:
        say("cond~", ":connective")
    for cue, sign in COMPARE_CUES.items():
        if any(tuple(c.words[i : i + len(cue)]) == cue for i in range(len(c.words))):
            signs = sorted({op.value for op in c.comparisons() if op.value in ("<", "<=", ">", ">=")} | {op.value for op in c.tree.find("op") if op.value in ("<", "<=", ">", ">=")})
            out.append(f"cmp:{'+'.join(signs) or 'none'}|{sign}")
            if signs and sign not in signs:
                say("cmp~")
    for n in c.tree.find("in"):
        denied = bool(DENIALS & set(c.words))
        out.append(f"in:{n.value.strip() or 'in'}|{'denied' if denied else 'no'}")
        if denied != bool(n.value):
            say("in~")
    items = [i for i in c.block.kid("select").kids]
    if c.words and c.words[0] in HEADS:
        head = c.question.lower().split(" of ")[0]
        asked_items = sum(p.lower() in head for p, *_ in c.wanted)
        gap = len(items) - asked_items
        if not c.functions():
            out.append(f"arity:{max(-2, min(2, gap))}")
            if gap:
                say("col+" if gap > 0 else "col-", ":list")
    out.append(f"items:{min(len(items), 4)}|{'agg' if c.functions() else 'plain'}|{'group' if group else 'flat'}")
    if not any(w.split(":")[0] in SAYS for w in out):
        say("ok")
    return out


def path_words(tree: Node, above: str = "") -> list[str]:
    """Role of each node with the clause it stands in: the tree as words."""
    here = tree.role if tree.role in ("select", "where", "group", "order", "on", "having", "limit") else above
    own = f"p:{here}/{tree.role}" + (f":{tree.value.upper()}" if tree.role in ("func", "bool", "op", "in", "sort") else "")
    return [own, *(w for k in tree.kids for w in path_words(k, here))]


# ---------------------------------------------------------------- findings


def findings(case: Case, growth: bool = False) -> list[Finding]:
    out: list[Finding] = []
    c, cat, tree = case, case.catalog, case.tree

    def add(slot: int, proof: bool, reason: str, slots: dict, nodes: list[Node], fix, elements: Iterable[str] = ()) -> None:
        out.append(Finding(slot, proof, reason, slots, nodes, fix, tuple(elements)))

    if c.block is None:
        add(12, True, "the text is no query", {"clause": "query"}, [tree], lambda: None)
        return out
    if not c.flat:
        return out
    _tables(c, add)
    _joins(c, add)
    _columns(c, add)
    _values(c, add)
    _clauses(c, add)
    if growth:
        for n in tree.find("in"):
            if bool(DENIALS & set(c.words)) != bool(n.value) and n.kids[1].role == "query":
                add(13, False, "the question denies it" if not n.value else "nothing denies it", {"predicate": render(n)}, [n], lambda n=n: setattr(n, "value", "" if n.value else "NOT "))
        for cue, sign in COMPARE_CUES.items():
            if any(tuple(c.words[i : i + len(cue)]) == cue for i in range(len(c.words))):
                for op in tree.find("op"):
                    if op.value in ("<", "<=", ">", ">=") and op.value != sign and op.value[0] == sign[0] and op.kids[1].role == "literal":
                        add(14, False, "the bound", {"used": op.value, "operator": sign}, [op], lambda op=op, sign=sign: setattr(op, "value", sign))
    return out


def _tables(c: Case, add) -> None:
    cat = c.catalog
    for r in c.relations:
        if r.value.lower() not in cat.columns:
            near = [t for t in c.asked if t not in c.read] or [t for t in cat.columns if t[:3] == r.value.lower()[:3]]
            if near:
                add(3, True, "no such table", {"used": r.value, "table": near[0]}, [r], lambda r=r, t=near[0]: setattr(r, "value", t), [near[0]])
    missing: dict[str, list[Node]] = {}
    aliases = {i.value.lower() for i in c.tree.find("item") if i.value}
    visible = {col for t in c.read for col in cat.columns.get(t, {})}
    for n in c.tree.find("column"):
        name = column_of(n)
        if name in visible or name in aliases or name == "*":
            continue
        owners = cat.owners(name)
        if len(owners) == 1:
            missing.setdefault(owners[0], []).append(n)
        elif not owners:
            want = [col for _, t, col, _ in c.wanted if t in c.read] or [v for v in sorted(visible) if stem(v) == stem(name)]
            if want:
                add(7, True, "no such column", {"used": name, "column": want[0]}, [n], lambda n=n, v=want[0]: setattr(n, "value", v))
    for t, nodes in missing.items():
        edge = next((cat.edge(have, t) for have in c.outer if cat.edge(have, t)), None)
        if edge or any(cat.path(have, t) for have in c.outer):
            slots = {"table": t, "edge": " = ".join(edge or ()), "columns": ", ".join(sorted({x.value for x in nodes}))}
            add(1, True, "a column's table is not read", slots, nodes, lambda t=t: c.add_table(t), [t, *(edge or ())])
    lost = [t for t in c.asked if t not in c.read and t not in missing]
    own = [t for t in c.outer if t in c.asked]
    # the question's table is not read, one with the same columns is
    if lost and len(c.outer) == 1 and c.outer[0] not in c.asked and not missing:
        used, want = c.outer[0], lost[0]
        swap = {col: v for col in cat.columns.get(used, {}) for v in cat.columns[want] if stem(v) == stem(col)}
        if all(column_of(n) in swap for n in c.used()):

            def change(want=want, swap=swap) -> None:
                next(r for r in c.relations if id(r) not in c.inner).value = want
                for n in c.used():
                    n.value = swap[column_of(n)]

            add(3, False, "the question names another table", {"used": used, "table": want}, [c.relations[0]], change, [used, want])
    elif lost and own:
        for t in lost:
            if any(cat.path(o, t) for o in own):
                add(1, False, "a table that is asked for is not read", {"table": t, "edge": "", "columns": ""}, [c.block.kid("from")], lambda t=t: c.add_table(t), [t])
    # a joined table gives nothing but its key, and nothing asks for it
    needed = near_tables(cat, c.asked)
    for j in c.tree.find("join"):
        if id(j) in c.inner or j.kids[1].role != "relation":
            continue
        t = j.kids[1].value.lower()
        rest = [o for o in c.outer if o != t]
        if t in cat.columns and t not in needed and not any(column_of(n) in cat.columns[t] for n in c.used()) and not any(cat.keeps_rows(o, t) for o in rest):

            def unjoin(j=j) -> None:
                for n in c.tree.walk():
                    for i, k in enumerate(n.kids):
                        if k is j:
                            n.kids[i] = j.kids[0]
                            return

            add(2, False, "nothing asks for the table", {"table": t}, [j], unjoin, [t])


def _joins(c: Case, add) -> None:
    cat = c.catalog
    for j in c.tree.find("join"):
        on = j.kid("on")
        if on is None or j.kids[1].role != "relation":
            continue
        right, cond = j.kids[1].value.lower(), on.kids[0]
        left = [r.value.lower() for r in j.kids[0].walk() if r.role == "relation"]
        if cond.role != "op" or cond.value != "=" or not all(k.role == "column" for k in cond.kids):
            continue
        names = {column_of(k) for k in cond.kids}
        for lt in left:
            edge = cat.edge(lt, right)
            plain = "." not in cond.kids[0].value + cond.kids[1].value
            if edge and plain and names & set(cat.columns[right]) and names & set(cat.columns[lt]) and names != set(edge):
                add(4, True, "not the foreign key", {"edge": " = ".join(edge)}, [cond], lambda cond=cond, edge=edge: setattr(cond, "kids", [Node("column", edge[0]), Node("column", edge[1])]), edge)


def _columns(c: Case, add) -> None:
    cat, select, group = c.catalog, c.block.kid("select"), c.block.kid("group")
    used = {column_of(n) for n in c.tree.find("column")}
    names = [column_of(i.kids[0]) for i in select.kids if i.kids[0].role == "column"]
    for i, item in enumerate(select.kids):
        if item.kids[0].role == "column" and names.count(column_of(item.kids[0])) > 1 and i:
            add(6, True, "returned twice", {"column": item.kids[0].value}, [item], lambda item=item: select.kids.remove(item) if item in select.kids else None)
            break
    wanted = {col for _, _, col, _ in c.wanted}
    values = {col for _, _, col in c.asked_values()}
    listing = bool(c.words) and c.words[0] in HEADS and group is None and not c.functions()
    if listing:
        head = c.question.lower().split(" of ")[0]
        want = [(p, col) for p, t, col, _ in c.wanted if p.lower() in head and t in c.outer]
        for p, col in want:
            if col not in names:
                short = piece_of(stem(col), lemma(p.lower())) or stem(col)
                add(5, False, "asked for, not returned", {"column": col}, [select], lambda col=col, short=short: select.kids.append(Node("item", short, [Node("column", col)])), [col])
        for item in list(select.kids):
            if want and item.kids[0].role == "column" and column_of(item.kids[0]) not in {col for _, col in want}:
                swap = next((col for _, col in want if col not in names and _same_kind(c, col, column_of(item.kids[0]))), None)
                if swap and len(select.kids) <= len(want):
                    add(7, False, "another column is asked for", {"used": item.kids[0].value, "column": swap}, [item], lambda item=item, swap=swap: setattr(item.kids[0], "value", swap), [swap])
                elif len(select.kids) > 1:
                    add(6, False, "returned, not asked for", {"column": item.kids[0].value}, [item], lambda item=item: select.kids.remove(item) if item in select.kids and len(select.kids) > 1 else None)
    elif group is None and not c.functions() and len(select.kids) > 2 and c.tree.kid("limit"):
        item = select.kids[-1]
        add(6, False, "returned, not asked for", {"column": render(item)}, [item], lambda: select.kids.remove(item) if item in select.kids else None)
    for f in c.functions():
        if f.kids and f.kids[0].role == "column":
            col = column_of(f.kids[0])
            want = next((w for _, t, w, _ in c.wanted if w not in used and _same_kind(c, w, col)), None)
            if want and col not in wanted and f.value.split()[0].upper() != "COUNT":
                add(7, False, "another column is asked for", {"used": col, "column": want}, [f], lambda f=f, want=want: setattr(f.kids[0], "value", want), [want])
            if f.value.upper() in ("SUM", "AVG") and cat.columns.get(c.owner(col) or "", {}).get(col) == "string":
                add(11, True, "a number function over text", {"used": f.value, "function": "COUNT"}, [f], lambda f=f: setattr(f, "value", "COUNT"))
    for op in c.comparisons():
        col = column_of(op.kids[0])
        if op.kids[1].value.startswith("'") or id(op) in c.inner:
            continue
        want = next((w for _, t, w, _ in c.wanted if w not in used and _same_kind(c, w, col)), None)
        if want and col not in wanted:
            add(7, False, "another column is compared", {"used": col, "column": want}, [op], lambda op=op, want=want: setattr(op.kids[0], "value", want), [want])
    if group is not None and group.kids[0].role == "column" and not group.value:
        col = column_of(group.kids[0])
        want = next((w for _, t, w, _ in c.wanted if w not in used and _same_kind(c, w, col)), None)
        if want and col not in wanted:

            def regroup(old=col, want=want) -> None:
                for n in [*group.find("column"), *select.find("column")]:
                    if column_of(n) == old:
                        n.value = want

            add(7, False, "another column is grouped", {"used": col, "column": want}, [group], regroup, [want])


def _same_kind(c: Case, a: str, b: str) -> bool:
    t = c.owner(a)
    return t is not None and c.catalog.columns[t].get(a) == c.catalog.columns.get(c.owner(b) or "", {}).get(b)


def _values(c: Case, add) -> None:
    cat, where = c.catalog, c.block.kid("where")
    asked = c.asked_values()
    literals = {n.value.strip("'") for n in c.tree.find("literal")}
    for op in c.comparisons():
        col, text = column_of(op.kids[0]), op.kids[1].value.strip("'")
        known = cat.values.get(col)
        if op.value not in ("=", "<>", "!=") or not op.kids[1].value.startswith("'") or not known:
            continue
        want = next((v for v, _, k in asked if k == col and v not in literals), None)
        if text not in known:
            want = next((v for v in known if v.lower() == text.lower()), None) or want or known[0]
            add(8, want.lower() == text.lower(), "no such value", {"used": text, "value": want}, [op], lambda op=op, want=want: setattr(op.kids[1], "value", f"'{want}'"), [col])
        elif want and text not in {v for v, _, _ in asked}:
            add(8, False, "another value is asked for", {"used": text, "value": want}, [op], lambda op=op, want=want: setattr(op.kids[1], "value", f"'{want}'"), [col])
        elif text not in {v for v, _, _ in asked} and where is not None and where.kids[0].role == "bool" and op in where.kids[0].kids:

            def drop(op=op) -> None:
                b = where.kids[0]
                b.kids = [k for k in b.kids if k is not op]
                if len(b.kids) == 1:
                    where.kids[0] = b.kids[0]

            add(10, False, "nothing asks for the condition", {"predicate": render(op)}, [op], drop, [col])
    compared = {column_of(op.kids[0]) for op in c.comparisons()}
    unsettled = {}
    for v, t, col in asked:
        if t in c.outer and v not in literals and (col not in compared or _either(c)):
            unsettled.setdefault(v, []).append((t, col))
    for v, places in unsettled.items():
        if len(places) == 1 or len({t for t, _ in places}) < len(places):
            t, col = places[0]
            alone = col in compared
            node = Node("op", "=", [Node("column", col), lit(v)])

            def put(node=node, alone=alone) -> None:
                now = c.block.kid("where")
                if alone and now is not None:
                    now.kids = [Node("bool", "OR", [now.kids[0], node])]
                else:
                    c.add_condition(node)

            add(9, False, "a value of the question is not used", {"predicate": render(node)}, [where or c.block], put, [f"{t}.{col}"])
    for b in c.tree.find("bool"):
        eq = [(column_of(k.kids[0]), k.kids[1].value) for k in b.kids if k.role == "op" and k.value == "=" and k.kids[0].role == "column" and k.kids[1].role == "literal"]
        clash = any(x[0] == y[0] and x[1] != y[1] for x in eq for y in eq)
        if b.value == "AND" and clash:
            add(10, True, "no row can satisfy both", {"predicate": render(b)}, [b], lambda b=b: setattr(b, "value", "OR"))
        elif b.value == "OR" and not _either(c) and id(b) not in c.inner:
            add(10, False, "nothing offers a choice", {"predicate": render(b)}, [b], lambda b=b: setattr(b, "value", "AND"))
    numbers, own = [op for op in c.comparisons() if not op.kids[1].value.startswith("'")], c.numbers()
    taken = {n.value for n in c.tree.find("literal")}
    free = [n for n in own if n not in taken]
    for op in numbers:
        if op.kids[1].value not in own and free and id(op) not in c.inner:
            add(10, False, "another number is asked for", {"predicate": render(op)}, [op], lambda op=op, n=free[0]: setattr(op.kids[1], "value", n))
    # a number that nothing uses, with the word that compares it and its column
    compares = next((s for cue, s in COMPARE_CUES.items() if any(tuple(c.words[i : i + len(cue)]) == cue for i in range(len(c.words)))), None)
    for n in free:
        if numbers or c.tree.kid("limit"):
            break
        target = next(((t, w) for _, t, w, _ in c.wanted if t in c.outer and cat.columns[t][w] in ("int", "bigint", "double") and w not in {column_of(x) for x in c.used()}), None)
        at = next((i for i, w in enumerate(c.words) if NUMBERS.get(w, w) == n), 0)
        key = next(((t, w) for t in c.outer for w in cat.columns.get(t, {}) if at and stem(w) == f"{lemma(c.words[at - 1])}key"), None)
        t, w = (target if compares else key or target) or ("", "")
        if w and c.block.kid("group") is None:
            node = Node("op", compares or "=", [Node("column", w), Node("literal", n)])
            add(9, False, "a number of the question is not used", {"predicate": render(node)}, [where or c.block], lambda node=node: c.add_condition(node), [f"{t}.{w}"])
        elif c.block.kid("group") is not None and compares and c.block.kid("having") is None:
            node = Node("having", "", [Node("op", compares, [Node("func", "COUNT", [Node("star", "*")]), Node("literal", n)])])
            add(9, False, "a number of the question is not used", {"predicate": render(node)}, [c.block], lambda node=node: c.block.kids.append(node))


def _either(c: Case) -> bool:
    return "or" in c.words


def _clauses(c: Case, add) -> None:
    select, group, order, limit = c.block.kid("select"), c.block.kid("group"), c.tree.kid("order"), c.tree.kid("limit")
    way = next((ORDER_CUES[w] for w in c.words if w in ("highest", "lowest", "most", "fewest") and not _bound(c, w)), None)
    if order is not None and way is not None and order.kids[0].value.replace("ASC", "") != way:
        add(12, False, "the other end comes first", {"clause": "ORDER BY"}, [order], lambda: setattr(order.kids[0], "value", way))
    own = [n for n in c.numbers()]
    if limit is not None and own and limit.kids[0].value not in own:
        add(12, False, "another number of rows", {"clause": "LIMIT"}, [limit], lambda: setattr(limit.kids[0], "value", own[0]))
    if limit is None and order is not None and own and way is not None:
        add(12, False, "the number of rows", {"clause": "LIMIT"}, [order], lambda: c.tree.kids.append(Node("limit", "", [Node("literal", own[0])])))
    if order is None and limit is not None and way is not None and len(select.kids) > 1:
        last = select.kids[-1].kids[0]
        first = select.kids[0].kids[0]

        def sort() -> None:
            node = Node("order", "", [Node("sort", way, [last.copy()]), Node("sort", "", [first.copy()])])
            c.tree.kids.insert(c.tree.kids.index(limit), node)

        add(12, False, "rows of no order", {"clause": "ORDER BY"}, [c.tree], sort)
    fns = c.functions()
    cue = next((f for w, f in FUNCTION_CUES.items() if w in c.words and not any(w in p.lower().split() for p, *_ in c.wanted)), None)
    numeric = next(((t, w) for _, t, w, _ in c.wanted if t in c.outer and c.catalog.columns[t][w] in ("int", "bigint", "double")), None)
    for f in fns:
        name = f.value.split()[0].upper()
        if cue and name != cue and group is None or cue and name != cue and cue != "COUNT":

            def call(f=f, cue=cue) -> None:
                f.value = cue
                if cue == "COUNT":
                    f.kids = [Node("star", "*")]
                elif f.kids and f.kids[0].role == "star" and numeric:
                    f.kids = [Node("column", numeric[1])]

            add(11, False, "the question asks for another function", {"used": name, "function": cue}, [f], call)
    plain = [i for i in select.kids if i.kids[0].role == "column"]
    if fns and plain and not select.find("window"):
        keys = [render(k).lower() for k in group.kids] if group else []
        for i in plain:
            if i.kids[0].value.lower() not in keys:
                asked = next((k for k in keys if k in {w for _, _, w, _ in c.wanted}), None)

                def regroup(i=i, asked=asked) -> None:
                    if asked:
                        i.kids[0].value = asked
                    elif group is not None:
                        group.kids.append(i.kids[0].copy())
                    else:
                        at = next((n for n, k in enumerate(c.block.kids) if k.role == "having"), len(c.block.kids))
                        c.block.kids.insert(at, Node("group", "", [i.kids[0].copy()]))

                add(12, True, "returned but not grouped", {"clause": "GROUP BY"}, [i], regroup)
                if asked:
                    add(7, False, "another column is grouped", {"used": i.kids[0].value, "column": asked}, [i], lambda: None)


def _bound(c: Case, word: str) -> bool:
    at = c.words.index(word)
    return at > 0 and c.words[at - 1] == "at"


def localized(case: Case, found: list[Finding]) -> list[tuple[int, str, tuple[str, ...], dict[str, str]]]:
    """(slot, smallest subtree over its nodes, schema elements, filled slots)."""
    return [(f.slot, render(minimal_subtree(case.tree, f.nodes)), f.elements, f.slots) for f in found]
