"""The question bank: templates filled with values of the tables, in two dev
sets of the sizes and levels that are asked, three shifted variants of the second, a
train set of other templates, and generators that are wrong at known rates.

A gold query is asked in many wordings, so that a bank of 1,534 questions needs
few executions. Everything is drawn from hashes of names: no state, no order."""

from __future__ import annotations

import zlib
from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import lru_cache

from .catalog import Catalog
from .perturb import compounds, mutations, rewrites


@dataclass(frozen=True)
class Question:
    question_id: str
    template: str
    level: str
    split: str
    text: str
    gold: str
    evidence: str = ""


def draw(*parts) -> float:
    return zlib.crc32("|".join(map(str, parts)).encode()) / 2**32


SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
REGIONS = ["AFRICA", "AMERICA", "ASIA", "EUROPE"]
PRIORITIES = {"urgent": "1-URGENT", "high": "2-HIGH", "medium": "3-MEDIUM", "low": "5-LOW"}
STATUS = {"open": "O", "filled": "F"}
EVENTS = ["click", "error", "purchase", "signup", "view"]
TYPES = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
COUNT = ["How many {0}?", "Count the {1}.", "What is the number of {1}?", "Tell me how many {0}.", "Give the number of {1}.", "Find out how many {0}.", "Report the number of {1}.", "How many {0} in all?"]
VALUE = ["What is the {0}?", "Give the {0}.", "Find the {0}.", "Tell me the {0}.", "Report the {0}.", "Show the {0}.", "I need the {0}.", "Look up the {0}."]
WHICH = ["Which {0}?", "Tell me which {0}.", "Find out which {0}.", "Say which {0}."]
LIST = ["List the {0}.", "Show the {0}.", "Give me the {0}.", "Return the {0}."]
ENDS = ["", " Please use the database.", " Answer from the tables.", " Only facts from the data."]


def joined(kind: list[str], short: str, noun: str = "") -> list[str]:
    """All wordings of one question: with a verb (``short``) or as a noun."""
    return [w.format(short, noun or short) + e for e in ENDS for w in kind]


def train_templates() -> list[tuple[str, str, list[str], str]]:
    """(template, level, wordings, gold)."""
    out = []
    add = lambda name, level, texts, gold: out.append((name, level, texts, gold))
    for x in (1000, 2500, 4000, 5500, 7000, 8500):
        add("sup_rich", "simple", joined(COUNT, f"suppliers have a balance above {x}", f"suppliers with a balance above {x}"), f"SELECT COUNT(*) AS n FROM supplier WHERE s_acctbal > {x}")
        add("sup_poor", "simple", joined(COUNT, f"suppliers have a balance below {x}", f"suppliers with a balance below {x}"), f"SELECT COUNT(*) AS n FROM supplier WHERE s_acctbal < {x}")
    for kind in TYPES:
        add("type_avg", "simple", joined(VALUE, f"average retail price of {kind} parts"), f"SELECT ROUND(AVG(p_retailprice), 2) AS v FROM part WHERE p_type = '{kind}'")
        add("type_max", "simple", joined(VALUE, f"largest retail price of {kind} parts"), f"SELECT MAX(p_retailprice) AS v FROM part WHERE p_type = '{kind}'")
        add("type_min", "simple", joined(VALUE, f"smallest retail price of {kind} parts"), f"SELECT MIN(p_retailprice) AS v FROM part WHERE p_type = '{kind}'")
        add("type_count", "simple", joined(COUNT, f"parts are of type {kind}", f"parts of type {kind}"), f"SELECT COUNT(*) AS n FROM part WHERE p_type = '{kind}'")
        add("type_lines", "moderate", joined(COUNT, f"lines belong to {kind} parts", f"lines of {kind} parts"), f"SELECT COUNT(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_type = '{kind}'")
        add("type_back", "moderate", joined(COUNT, f"returned lines belong to {kind} parts", f"returned lines of {kind} parts"), f"SELECT COUNT(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_type = '{kind}' AND l_returnflag = 'R'")
        add("type_never", "challenging", joined(COUNT, f"{kind} parts were never returned", f"{kind} parts that were never returned"), f"SELECT COUNT(*) AS n FROM part WHERE p_type = '{kind}' AND p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R')")
    for k in (1, 4, 7, 9):
        add("nat_list", "simple", joined(LIST, f"name and balance of suppliers of nation {k}"), f"SELECT s_name AS name, s_acctbal AS bal FROM supplier WHERE s_nationkey = {k}")
        add("nat_names", "simple", joined(LIST, f"name of suppliers of nation {k}"), f"SELECT s_name AS name FROM supplier WHERE s_nationkey = {k}")
        add("size_least", "simple", joined(COUNT, f"parts have a size of at least {5 * k}", f"parts with a size of at least {5 * k}"), f"SELECT COUNT(*) AS n FROM part WHERE p_size >= {5 * k}")
        add("size_most", "simple", joined(COUNT, f"parts have a size of at most {5 * k}", f"parts with a size of at most {5 * k}"), f"SELECT COUNT(*) AS n FROM part WHERE p_size <= {5 * k}")
        add("top_orders", "simple", joined(WHICH, f"{k + 2} orders have the highest total price"), f"SELECT o_orderkey AS k, o_totalprice AS v FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT {k + 2}")
        add("low_suppliers", "simple", joined(WHICH, f"{k + 1} suppliers have the lowest balance"), f"SELECT s_suppkey AS k, s_acctbal AS v FROM supplier ORDER BY s_acctbal, s_suppkey LIMIT {k + 1}")
    for word, p in PRIORITIES.items():
        for status, o in STATUS.items():
            add("prio_status", "moderate", joined(COUNT, f"{word} orders are {status}", f"{word} orders that are {status}"), f"SELECT COUNT(*) AS n FROM orders WHERE o_orderpriority = '{p}' AND o_orderstatus = '{o}'")
    for status, o in STATUS.items():
        add("status_lines", "moderate", joined(COUNT, f"lines belong to {status} orders", f"lines of {status} orders"), f"SELECT COUNT(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderstatus = '{o}'")
        add("status_mean", "simple", joined(VALUE, f"average total price of {status} orders"), f"SELECT ROUND(AVG(o_totalprice), 2) AS v FROM orders WHERE o_orderstatus = '{o}'")
    for i, a in enumerate(EVENTS):
        b = EVENTS[(i + 1) % 5]
        add("two_events", "simple", joined(COUNT, f"events are {a} or {b}", f"events that are {a} or {b}"), f"SELECT COUNT(*) AS n FROM events WHERE event_type = '{a}' OR event_type = '{b}'")
    for r in REGIONS:
        add("reg_nations", "moderate", joined(COUNT, f"nations lie in {r}", f"nations in {r}"), f"SELECT COUNT(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = '{r}'")
        add("reg_suppliers", "moderate", joined(COUNT, f"suppliers lie in {r}", f"suppliers in {r}"), f"SELECT COUNT(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = '{r}'")
    for text, table, col, what, fn in (
        ("total price of orders per status", "orders", "o_orderstatus", "o_totalprice", "SUM"),
        ("average total price of orders per priority", "orders", "o_orderpriority", "o_totalprice", "AVG"),
        ("average retail price of parts per type", "part", "p_type", "p_retailprice", "AVG"),
        ("total retail price of parts per brand", "part", "p_brand", "p_retailprice", "SUM"),
        ("average value of events per event type", "events", "event_type", "value", "AVG"),
    ):
        add(f"group_{table}_{col}", "simple", joined(VALUE, text if text.startswith("average") or "total p" in text else text), f"SELECT {col} AS g, ROUND({fn}({what}), 2) AS v FROM {table} GROUP BY {col}")
    for n in (60, 70, 80):
        add("brand_many", "challenging", joined(WHICH, f"brands have more than {n} parts"), f"SELECT p_brand AS g, COUNT(*) AS n FROM part GROUP BY p_brand HAVING COUNT(*) > {n}")
        add("nation_sup", "challenging", joined(WHICH, f"{n // 20} nations have the most suppliers"), f"SELECT n_name AS g, COUNT(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name ORDER BY COUNT(*) DESC, n_name LIMIT {n // 20}")
    return out


def dev_templates() -> list[tuple[str, str, list[str], str]]:
    out = []
    add = lambda name, level, texts, gold: out.append((name, level, texts, gold))
    for i, s in enumerate(SEGMENTS):
        add("seg_count", "simple", joined(COUNT, f"customers are in the {s} segment", f"customers of the {s} segment"), f"SELECT COUNT(*) AS n FROM customer WHERE c_mktsegment = '{s}'")
        add("seg_balance", "simple", joined(VALUE, f"average balance of customers in the {s} segment"), f"SELECT ROUND(AVG(c_acctbal), 2) AS v FROM customer WHERE c_mktsegment = '{s}'")
        add("seg_richest", "simple", joined(VALUE, f"largest balance of customers in the {s} segment"), f"SELECT MAX(c_acctbal) AS v FROM customer WHERE c_mktsegment = '{s}'")
        add("seg_orders", "moderate", joined(COUNT, f"orders did customers of the {s} segment place", f"orders of customers of the {s} segment"), f"SELECT COUNT(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = '{s}'")
        for status, o in STATUS.items():
            add("seg_status", "moderate", joined(COUNT, f"{status} orders did {s} customers place", f"{status} orders of {s} customers"), f"SELECT COUNT(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = '{s}' AND o_orderstatus = '{o}'")
            add("seg_never", "challenging", joined(COUNT, f"{s} customers have never placed a {status} order", f"{s} customers that never placed a {status} order"), f"SELECT COUNT(*) AS n FROM customer WHERE c_mktsegment = '{s}' AND c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderstatus = '{o}')")
        add("seg_prices", "challenging", joined(VALUE, f"total price of orders of {s} customers per priority"), f"SELECT o_orderpriority AS g, ROUND(SUM(o_totalprice), 2) AS v FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = '{s}' GROUP BY o_orderpriority")
        k = 3 * i + 2
        add("nat_clients", "simple", joined(LIST, f"name and balance of customers of nation {k}"), f"SELECT c_name AS name, c_acctbal AS bal FROM customer WHERE c_nationkey = {k}")
        add("nat_client_names", "simple", joined(LIST, f"name of customers of nation {k}"), f"SELECT c_name AS name FROM customer WHERE c_nationkey = {k}")
        add("top_parts", "simple", joined(WHICH, f"{i + 3} parts have the highest retail price"), f"SELECT p_partkey AS k, p_retailprice AS v FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT {i + 3}")
        add("low_clients", "simple", joined(WHICH, f"{i + 2} customers have the lowest balance"), f"SELECT c_custkey AS k, c_acctbal AS v FROM customer ORDER BY c_acctbal, c_custkey LIMIT {i + 2}")
        add("poor_clients", "simple", joined(COUNT, f"customers have a balance below {1500 * i}", f"customers with a balance below {1500 * i}"), f"SELECT COUNT(*) AS n FROM customer WHERE c_acctbal < {1500 * i}")
        add("lines_least", "simple", joined(COUNT, f"lines have a quantity of at least {8 * i + 6}", f"lines with a quantity of at least {8 * i + 6}"), f"SELECT COUNT(*) AS n FROM lineitem WHERE l_quantity >= {8 * i + 6}")
        add("lines_most", "simple", joined(COUNT, f"lines have a quantity of at most {8 * i + 4}", f"lines with a quantity of at most {8 * i + 4}"), f"SELECT COUNT(*) AS n FROM lineitem WHERE l_quantity <= {8 * i + 4}")
        add("brand_parts", "simple", joined(LIST, f"name and size of parts of brand Brand#{i + 11}"), f"SELECT p_name AS name, p_size AS size FROM part WHERE p_brand = 'Brand#{i + 11}'")
        add("event_sum", "simple", joined(VALUE, f"total value of {EVENTS[i]} events"), f"SELECT ROUND(SUM(value), 2) AS v FROM events WHERE event_type = '{EVENTS[i]}'")
        add("size_back", "moderate", joined(COUNT, f"returned lines belong to parts of size {7 * i + 11}", f"returned lines of parts of size {7 * i + 11}"), f"SELECT COUNT(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_size = {7 * i + 11} AND l_returnflag = 'R'")
        add("brand_lines", "moderate", joined(COUNT, f"lines belong to parts of brand Brand#{i + 16}", f"lines of parts of brand Brand#{i + 16}"), f"SELECT COUNT(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_brand = 'Brand#{i + 16}'")
    pairs = list(PRIORITIES.items())
    for i, (word, p) in enumerate(pairs):
        other, q = pairs[(i + 1) % 4]
        add("prio_count", "simple", joined(COUNT, f"orders have {word} priority", f"orders of {word} priority"), f"SELECT COUNT(*) AS n FROM orders WHERE o_orderpriority = '{p}'")
        add("prio_pair", "simple", joined(COUNT, f"orders are {word} or {other}", f"orders that are {word} or {other}"), f"SELECT COUNT(*) AS n FROM orders WHERE o_orderpriority = '{p}' OR o_orderpriority = '{q}'")
        add("never_prio", "challenging", joined(COUNT, f"customers never placed a {word} order", f"customers that never placed a {word} order"), f"SELECT COUNT(*) AS n FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '{p}')")
    for r in REGIONS:
        add("reg_clients", "moderate", joined(COUNT, f"customers lie in {r}", f"customers in {r}"), f"SELECT COUNT(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = '{r}'")
        add("reg_balance", "moderate", joined(VALUE, f"average balance of customers in {r}"), f"SELECT ROUND(AVG(c_acctbal), 2) AS v FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = '{r}'")
    for status, o in STATUS.items():
        add("status_max", "simple", joined(VALUE, f"largest total price of {status} orders"), f"SELECT MAX(o_totalprice) AS v FROM orders WHERE o_orderstatus = '{o}'")
        add("seg_open_many", "challenging", joined(WHICH, f"segments have more than {150 if o == 'F' else 200} {status} orders"), f"SELECT c_mktsegment AS g, COUNT(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_orderstatus = '{o}' GROUP BY c_mktsegment HAVING COUNT(*) > {150 if o == 'F' else 200}")
    for text, col in (("return flag", "l_returnflag"), ("line status", "l_linestatus")):
        add("line_total", "simple", joined(VALUE, f"total quantity of lines per {text}"), f"SELECT {col} AS g, ROUND(SUM(l_quantity), 2) AS v FROM lineitem GROUP BY {col}")
    add("seg_total", "simple", joined(VALUE, "total balance of customers per segment"), "SELECT c_mktsegment AS g, ROUND(SUM(c_acctbal), 2) AS v FROM customer GROUP BY c_mktsegment")
    for n in (3, 5):
        add("nation_clients", "challenging", joined(WHICH, f"{n} nations have the most customers"), f"SELECT n_name AS g, COUNT(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name ORDER BY COUNT(*) DESC, n_name LIMIT {n}")
    return out


#: Questions of each level.
SIZES = {"a": {"simple": 925, "moderate": 464, "challenging": 145}, "b": {"easy": 248, "medium": 446, "hard": 174, "extra": 166}}
#: Questions of the shifted variants of the second set.
SHIFTED = {"realistic": 508, "synonym": 1034, "domain": 535}


def hardness(level: str, gold: str) -> str:
    """Four levels from three: plain questions of one table are easy, groups,
    orders and alternatives medium, joins hard, the rest extra."""
    if level == "challenging":
        return "extra"
    if level == "moderate":
        return "hard"
    return "medium" if any(w in gold for w in (" OR ", "GROUP BY", "ORDER BY", "MAX(", "SUM(", "AVG(")) or gold.count(" AS ") > 1 else "easy"


def filled(templates, split: str, sizes: dict[str, int], levels: Callable[[str, str], str], prefix: str) -> list[Question]:
    """Questions of the asked number for each level: every gold in turn, each
    time in its next wording."""
    out = []
    for level, many in sizes.items():
        own = [t for t in templates if levels(t[1], t[3]) == level]
        own.sort(key=lambda t: draw(prefix, t[0], t[3]))
        ways = [(wording, t) for wording in range(max(len(t[2]) for t in own)) for t in own if wording < len(t[2])]
        if len(ways) < many:
            raise ValueError(f"only {len(ways)} wordings for {many} questions of level {level}")
        out += [Question(f"{prefix}{level[:2]}{i:04d}", t[0], level, split, t[2][(w + int(draw(prefix, t[3]) * len(t[2]))) % len(t[2])], t[3]) for i, (w, t) in enumerate(ways[:many])]
    return out


@lru_cache(1)
def train_questions() -> list[Question]:
    """Three wordings of every gold of the train templates."""
    templates = train_templates()
    return [Question(f"t{i:03d}-{w}", t[0], t[1], "train", t[2][(5 * w + i) % len(t[2])], t[3]) for i, t in enumerate(templates) for w in range(3)]


@lru_cache(4)
def dev_questions(bank: str = "a", share: float = 1.0) -> list[Question]:
    """The dev set "a" (three levels) or "b" (four); ``share`` < 1 for tests."""
    sizes = {k: max(1, round(n * share)) for k, n in SIZES[bank].items()}
    return filled(dev_templates(), "dev", sizes, (lambda level, gold: level) if bank == "a" else hardness, bank)


#: Words of the shifted variants. None of them is in a name or the train split.
VARIANTS = {
    "base": {},
    "realistic": {" segment": " business", "retail price": "tag", "total price": "worth", "name and balance": "name and money", "a balance": "money", "quantity of": "count of"},
    "synonym": {"customers": "clients", "balance": "funds", "suppliers": "vendors", "parts": "goods", "average": "mean", "largest": "greatest", "returned": "sent-back"},
    "domain": {"open": "pending", "returned": "refunded", "urgent": "top-urgency", "filled": "delivered", "highest": "steepest", "lowest": "leanest"},
}


def variant(text: str, kind: str) -> str:
    for a, b in VARIANTS[kind].items():
        text = text.replace(a, b)
    return text


def shifted(kind: str, share: float = 1.0) -> list[Question]:
    """A variant of the second set: those questions that its words change come
    first, up to the variant's size."""
    base = dev_questions("b", share)
    if kind == "base":
        return base
    base = sorted(base, key=lambda q: (variant(q.text, kind) == q.text, draw(kind, q.question_id)))
    return [replace(q, text=variant(q.text, kind)) for q in base[: max(1, round(SHIFTED[kind] * share))]]


def leaks(train: list[Question], dev: list[Question], size: int = 8) -> dict[str, int]:
    """What the splits share: templates, gold queries, whole questions, and dev
    questions that hold a run of ``size`` words of a train question."""
    runs = lambda q: {tuple(w[i : i + size]) for w in [q.text.lower().split()] for i in range(len(w) - size + 1)}
    known = set().union(*map(runs, train)) if train else set()
    same = lambda f: len({f(q) for q in train} & {f(q) for q in dev})
    return {"templates": same(lambda q: q.template), "golds": same(lambda q: q.gold), "texts": same(lambda q: q.text.lower()), "word_runs": sum(bool(runs(q) & known) for q in dev)}


#: Share of right queries, by bank and level.
RIGHT = {
    "G1": {"a": {"simple": 0.6335, "moderate": 0.4418, "challenging": 0.4552}, "b": {"easy": 0.9153, "medium": 0.7242, "hard": 0.7644, "extra": 0.5843}},
    "G2": {"a": {"simple": 0.7546, "moderate": 0.6466, "challenging": 0.6690}, "b": {"easy": 0.9274, "medium": 0.8857, "hard": 0.7931, "extra": 0.6988}},
}


@dataclass
class NoisyBackbone:
    """A generator that is wrong at a known rate for each level. The wrong
    queries of a gold are few, so that its questions share mistakes: ``kinds`` of
    them, drawn from rewrites, pairs of rewrites and mutations that no single
    rewrite makes. A further sample repeats the first answer in ``shared`` of the
    questions. Candidates that change no result are passed over. ``failing``:
    share of wrong answers that fail, where a gold has such."""

    name: str
    seed: int = 0
    kinds: int = 4
    shared: float = 0.8
    failing: float = 0.1
    pools: dict = field(default_factory=dict)

    def options(self, gold: str, catalog: Catalog) -> list[tuple[str, tuple[int, ...]]]:
        """(query, types) in this generator's order, best first."""
        if gold not in self.pools:
            made = [(t, (s,), "rule") for s, t in rewrites(gold, catalog) if s <= 12]
            made += [(t, tuple(sorted(p)), "pair") for p, t in compounds(gold, catalog) if max(p) <= 12]
            made += [(t, s, "free") for s, t in mutations(gold, catalog)]
            # half are free mutations, then rules, then pairs
            weight = {"rule": 1.0, "pair": 0.5, "free": 2.0}
            made.sort(key=lambda m: draw(self.seed, gold, m[0]) ** (1 / weight[m[2]]), reverse=True)
            self.pools[gold] = list({t: (t, s) for t, s, _ in made}.values())
        return self.pools[gold]

    def wrong(self, gold: str, catalog: Catalog, known: dict) -> list[tuple[str, tuple[int, ...]]]:
        """Of those that were run, the first ``kinds`` that differ from gold."""
        return [(t, s) for t, s in self.options(gold, catalog) if t in known and known[t] is not None and known[t] != known[gold]][: self.kinds]

    def fails(self, gold: str, catalog: Catalog, known: dict) -> list[tuple[str, tuple[int, ...]]]:
        return [(t, s) for t, s in self.options(gold, catalog) if t in known and known[t] is None]

    def answers(self, bank: list[Question], bank_name: str, catalog: Catalog, known: dict, sample: int = 0) -> dict[str, tuple[str, tuple[int, ...]]]:
        """question_id -> (query, types). The share of right queries of a level
        is met exactly in the first sample, as far as golds can be got wrong."""
        out = {}
        for level in sorted({q.level for q in bank}):
            own = sorted((q for q in bank if q.level == level), key=lambda q: draw(self.name, self.seed, q.question_id))
            right = round(RIGHT[self.name][bank_name][level] * len(own))
            for i, q in enumerate(own):
                wrong, failing = self.wrong(q.gold, catalog, known), self.fails(q.gold, catalog, known)
                miss, pick = i >= right, draw(self.name, self.seed, q.question_id, "pick")
                if sample and draw(self.name, self.seed, q.question_id, sample) >= self.shared:
                    miss, pick = draw(self.name, q.question_id, sample, "miss") * len(own) >= right, draw(self.name, q.question_id, sample, "pick")
                if not miss or not wrong + failing:
                    out[q.question_id] = (q.gold, ())
                elif failing and (not wrong or pick < self.failing):
                    out[q.question_id] = failing[int(pick * 997) % len(failing)]
                else:
                    out[q.question_id] = wrong[int(pick * len(wrong))]
        return out


G1, G2 = NoisyBackbone("G1", 1), NoisyBackbone("G2", 2)
