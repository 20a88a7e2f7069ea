"""Personal data: patterns propose, checksums confirm, context words score.

Everything is a Spark SQL expression over one row; there is no shuffle and no
Python. A pattern's matches come from ``regexp_extract_all`` and their places
from the pieces between them (``split`` by the same pattern): a match starts
after all earlier pieces and matches. Quantifiers are possessive and a match
may start only where a run of its characters starts (or where the match before
it ended), which gives the same matches as the plain patterns, in linear time
and without recursion on long runs. Account numbers have no pattern for their
end: what follows may look like more of them, so every end is tried.

Null texts count as empty: no spans. Repeated rows are kept.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Kind:
    """``needs``: a text without this pattern has no match. ``words``: whole
    words that make a span likelier within ``reach`` characters before it."""

    name: str
    pattern: str
    needs: str
    words: str
    prior: float


KINDS = [
    Kind("email", r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "@", "e-?mails?|mail|contact|write|correo|courriel", 0.9),
    Kind("ip", r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", ".", "ip|ipv4|host|hosts|server|servers|addr|address", 0.6),
    Kind("card", r"(?:\G|(?<![0-9]))[0-9](?:[\x20-]?+[0-9])++", "", "cards?|visa|pay|paid|payment|credit|tarjeta|karte|carte", 0.7),
    Kind("phone", r"\+[0-9][\x20().0-9-]+[0-9]", "+", "phones?|telephone|tel|call|mobile|fax", 0.7),
]
#: Added by the method: account numbers with two check digits (modulo 97). The
#: pattern takes the four characters that one may start with.
ACCOUNT = Kind("iban", r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?=(?:\x20?[A-Z0-9]){11})", "", "iban|bank|accounts?|konto|compte|cuenta", 0.8)
#: All that can belong to one: at most 34 characters and a space before each of
#: the last 30. One more character tells whether a word ends there.
ACCOUNT_RUN, ACCOUNT_REACH = r"^[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]){11,30}+", 65


def digits_of(text: Column) -> Column:
    return F.regexp_replace(text, "[^0-9]", "")


def characters(text: Column) -> Column:
    """A non-empty string's characters."""
    return F.transform(F.sequence(F.lit(1), F.greatest(F.length(text), F.lit(1))), lambda i: F.substring(text, i, F.lit(1)))


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the Luhn check."""
    values = F.transform(characters(F.reverse(digits)), lambda d, i: F.when(i % 2 == 0, d.cast("int")).otherwise((d.cast("int") * 2) % 10 + F.when(d.cast("int") > 4, 1).otherwise(0)))
    return F.aggregate(values, F.lit(0), lambda a, d: a + d) % 10 == 0


def mod97(text: Column) -> Column:
    """Whether an account number, its first four characters moved to its end and
    its letters read as 10 to 35, leaves 1 when divided by 97."""
    packed = F.regexp_replace(text, r"\x20", "")
    moved = F.concat(F.substring(packed, 5, 40), F.substring(packed, 1, 4))
    value = lambda c: F.when(c.rlike("[0-9]"), F.ascii(c) - 48).otherwise(F.ascii(c) - 55)
    step = lambda a, c: (a * F.when(value(c) > 9, 100).otherwise(10) + value(c)) % 97
    return F.aggregate(characters(moved), F.lit(0), step) == 1


def confirmed(kind: str, text: Column) -> Column:
    n = F.length(digits_of(text))
    if kind == "ip":
        return F.forall(F.split(text, r"\."), lambda p: F.length(F.ltrim(p, F.lit("0"))) < 4) & F.forall(F.split(text, r"\."), lambda p: F.coalesce(F.substring(F.ltrim(p, F.lit("0")), 1, 4).try_cast("int"), F.lit(0)) <= 255)
    if kind == "card":
        return F.when(n.between(14, 19), luhn(digits_of(text))).otherwise(False)
    if kind == "phone":
        return n.between(10, 15)
    return F.lit(True)


def account_length(ahead: Column) -> Column:
    """Length of the longest account number, of 15 to 34 letters and digits up to
    a word's end, that a text starts with; 0 for none."""
    run = F.length(F.regexp_extract(ahead, ACCOUNT_RUN, 0))
    ends = F.when(run > 0, F.sequence(run, F.lit(15), F.lit(-1))).otherwise(F.expr("cast(array() as array<int>)"))
    start = lambda n: F.substring(ahead, F.lit(1), n)
    word_end = lambda n: F.substring(ahead, n, F.lit(2)).rlike("^[A-Z0-9](?![A-Za-z0-9])")
    fits = F.filter(ends, lambda n: word_end(n) & (F.length(F.regexp_replace(start(n), r"\x20", "")) >= 15) & mod97(start(n)))
    return F.coalesce(F.array_max(fits), F.lit(0))


def accounts(text: Column, starts: Column) -> Column:
    """The account numbers at these starts, without those inside an earlier one."""
    ahead = lambda s: F.substring(text, s["start"] + 1, F.lit(ACCOUNT_REACH))
    ended = F.transform(starts, lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), (s["start"] + account_length(ahead(s))).cast("int").alias("stop")))
    whole = F.transform(F.filter(ended, lambda s: s["stop"] > s["start"]), lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["stop"].alias("stop"), F.substring(text, s["start"] + 1, s["stop"] - s["start"]).alias("text")))
    empty = F.expr("cast(array() as array<struct<kind:string,start:int,stop:int,text:string>>)")
    step = lambda acc, s: F.when(s["start"] >= acc["at"], F.struct(s["stop"].alias("at"), F.concat(acc["out"], F.array(s)).alias("out"))).otherwise(acc)
    return F.aggregate(whole, F.struct(F.lit(0).alias("at"), empty.alias("out")), step, lambda acc: acc["out"])


def proposals(text: Column, kind: Kind) -> Column:
    """array<struct<kind,start,stop,text>> of a kind's confirmed matches in order."""
    empty = F.expr("cast(array() as array<struct<kind:string,start:int,stop:int,text:string>>)")
    found = F.regexp_extract_all(text, F.lit(kind.pattern), F.lit(0))
    pieces = F.split(text, kind.pattern, -1)
    item = lambda at, m: F.struct(F.lit(kind.name).alias("kind"), at.cast("int").alias("start"), (at + F.length(m)).cast("int").alias("stop"), m.alias("text"))
    walk = lambda acc, z: F.struct((acc["at"] + F.length(z["p"]) + F.length(z["m"])).alias("at"), F.concat(acc["out"], F.array(item(acc["at"] + F.length(z["p"]), z["m"]))).alias("out"))
    zipped = F.filter(F.arrays_zip(pieces.alias("p"), found.alias("m")), lambda z: z["m"].isNotNull())
    spans = F.aggregate(zipped, F.struct(F.lit(0).alias("at"), empty.alias("out")), walk, lambda acc: acc["out"])
    spans = accounts(text, spans) if kind is ACCOUNT else F.filter(spans, lambda s: confirmed(kind.name, s["text"]))
    likely = F.contains(text, F.lit(kind.needs)) if kind.needs else text.rlike(kind.pattern)
    return F.when(likely, spans).otherwise(empty)


def with_pii(df: DataFrame, text: str = "text", reach: int = 48, out: str = "found") -> DataFrame:
    """All columns of ``df`` and ``out``: an array of (start, rank, stop, kind,
    text, score) by start, then kind as listed; places are code points from 0,
    the end exclusive. The score is the kind's prior, raised by a context word in
    the ``reach`` characters before the span. A confirmed account number is
    listed too; it may overlap a span of another kind."""
    kinds, own = [*KINDS, ACCOUNT], df.columns
    rows = df.withColumn("_pii_text", F.coalesce(F.col(f"`{text}`"), F.lit("")))
    for k in kinds:
        rows = rows.withColumn(f"_pii_{k.name}", proposals(F.col("_pii_text"), k))

    def scored(s: Column) -> Column:
        window = F.lower(F.substring(F.col("_pii_text"), F.greatest(s["start"] - reach, F.lit(0)) + 1, F.least(F.lit(reach), s["start"])))
        score, rank = F.lit(0.0), F.lit(9)
        for i, k in reversed([*enumerate(kinds)]):
            near = window.rlike(rf"(?<![\p{{L}}\p{{N}}])(?:{k.words})(?![\p{{L}}\p{{N}}])")
            score = F.when(s["kind"] == k.name, F.lit(k.prior) + F.when(near, F.lit(round(0.5 * (1 - k.prior), 4))).otherwise(F.lit(0.0))).otherwise(score)
            rank = F.when(s["kind"] == k.name, F.lit(i)).otherwise(rank)
        return F.struct(s["start"].alias("start"), rank.alias("rank"), s["stop"].alias("stop"), s["kind"].alias("kind"), s["text"].alias("text"), score.alias("score"))

    every = F.concat(*[F.col(f"_pii_{k.name}") for k in kinds])
    return rows.select(*[F.col(f"`{c}`") for c in own if c != out], F.array_sort(F.transform(every, scored)).alias(out))


def find_pii(df: DataFrame, key: str = "doc_id", text: str = "text", reach: int = 48) -> DataFrame:
    """One row per input row: key and ``found`` (see ``with_pii``)."""
    return with_pii(df.select(F.col(f"`{key}`").alias("_pii_key"), F.col(f"`{text}`").alias("_pii_body")), "_pii_body", reach).select(F.col("_pii_key").alias(key), "found")


def redact(df: DataFrame, text: str = "text", reach: int = 48) -> DataFrame:
    """``df``, row by row, with each span in its text replaced by its kind in
    brackets; of spans that overlap the first stands. A null text stays null."""
    body = F.col(f"`{text}`")
    step = lambda acc, s: F.when(s["start"] >= acc["at"], F.struct(s["stop"].alias("at"), F.concat(acc["out"], F.substring(body, acc["at"] + 1, s["start"] - acc["at"]), F.lit("["), s["kind"], F.lit("]")).alias("out"))).otherwise(F.struct(F.greatest(acc["at"], s["stop"]).alias("at"), acc["out"].alias("out")))
    done = F.aggregate("_pii_found", F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), step, lambda acc: F.concat(acc["out"], F.substring(body, acc["at"] + 1, F.length(body))))
    return with_pii(df, text, reach, "_pii_found").withColumn(text, done).select(*[F.col(f"`{c}`") for c in df.columns])


def span_text(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["stop"].cast("string"))), ",")


def pii_digest(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The contract's columns, from the operator's spans."""
    base = F.filter("found", lambda s: s["kind"] != ACCOUNT.name)
    count = lambda name: F.size(F.filter("found", lambda s: s["kind"] == name)).cast("long").alias(f"n_{name}")
    return find_pii(df, key, text).select(key, *[count(k.name) for k in KINDS], F.sha2(span_text(base), 256).alias("base_sha256"), span_text(F.col("found")).alias("spans"), F.round(F.aggregate("found", F.lit(0.0), lambda a, s: F.greatest(a, s["score"])), 4).alias("top_score"))
