"""URL filter: all wildcard rules run at once as one bit-parallel automaton.

Each rule is a glob over the canonical URL ``.host#path``. ``#`` occurs in
neither part, so it separates them, and the leading dot lets ``*.rule`` fit a
host and its subdomains alike. Every rule gets a run of bits in a state vector
of as many 64-bit words as are needed. A step shifts the vector by one (with
carries between words), keeps the bits whose rule accepts the byte, and adds
the states that a star lets stay (Shift-And). The step is one numpy expression
over all URLs of a batch; there is no shuffle and no state besides the masks,
so hot hosts cost the same as others.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import U, column_bytes

SEPARATOR = "#"


@dataclass(frozen=True)
class UrlRule:
    """``host`` fits itself and its subdomains ("*" fits all); ``path`` is a
    glob, and a path without a trailing star must fit to the end."""

    name: str | None
    host: str
    path: str
    verdict: str

    @property
    def glob(self) -> str:
        return ("*" if self.host == "*" else f"*.{self.host}") + SEPARATOR + self.path


def prefix_rule(verdict: str, text: str) -> UrlRule:
    """``net/es/``: this host and its subdomains, paths that start with /es/."""
    host, _, path = text.partition("/")
    return UrlRule(text, host, f"/{path}*", verdict)


class GlobAutomaton:
    """Packed Shift-And masks of many globs; ``*`` any run, other bytes as they are."""

    def __init__(self, globs: Sequence[str]):
        accept: list[tuple[int, int]] = []
        stay, self.first, self.last, at = [], [], [], 0
        for glob in globs:
            self.first.append(at)
            for byte in glob.encode():
                if byte == 0x2A:
                    stay.append(at)
                else:
                    at += 1
                    accept.append((at, byte))
            self.last.append(at)
            at += 1
        self.words = at // 64 + 1
        self.accept = np.zeros((256, self.words), U)
        for bit, byte in accept:
            self.accept[byte, bit >> 6] |= U(1 << (bit & 63))
        self.stay, self.start = self._mask(stay), self._mask(self.first)

    def _mask(self, bits: Sequence[int]) -> np.ndarray:
        out = np.zeros(self.words, U)
        for bit in bits:
            out[bit >> 6] |= U(1 << (bit & 63))
        return out

    def run(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Rows by rules: which globs accept which whole strings."""
        lengths = np.diff(offsets)
        order = np.argsort(-lengths, kind="stable")
        starts, lengths = offsets[:-1][order], lengths[order]
        state = np.tile(self.start, (len(order), 1))
        active = np.searchsorted(-lengths, -np.arange(lengths[0] if len(lengths) else 0), "left")
        for step, live in enumerate(active):
            now = state[:live]
            moved = now << U(1)
            moved[:, 1:] |= now[:, :-1] >> U(63)
            state[:live] = (moved & self.accept[data[starts[:live] + step]]) | (now & self.stay)
        out = np.empty((len(order), len(self.last)), bool)
        for k, bit in enumerate(self.last):
            out[order, k] = (state[:, bit >> 6] >> U(bit & 63)) & U(1) != 0
        return out


def host_and_path(url: str = "url") -> tuple[F.Column, F.Column]:
    """Columns of the host (A-Z in lower case) and the path; null: empty."""
    parts = r"(?s)://([^/?#]*)([^?#]*)"
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    text = F.coalesce(F.col(url), F.lit(""))
    return F.translate(F.regexp_extract(text, parts, 1), upper, upper.lower()), F.regexp_extract(text, parts, 2)


def filter_urls(df: DataFrame, rules: Sequence[UrlRule], default: str = "allow", key: str = "page_id", url: str = "url") -> DataFrame:
    """One row per input row: key, host, path, rule, verdict.

    The longest rule that fits wins, of equal ones the first; unnamed rules
    come after all named ones. Where none fits, rule is null and the verdict is
    ``default``. A null or malformed URL has an empty host and path, which no
    named rule fits. Other columns are left behind; repeated rows are kept."""
    order = sorted(range(len(rules)), key=lambda k: (rules[k].name is None, -len(rules[k].name or rules[k].glob), k))
    ranked = [rules[k] for k in order]
    names = pa.array([r.name for r in ranked] + [None], pa.string())
    verdicts = pa.array([r.verdict for r in ranked] + [default], pa.string())
    automaton = GlobAutomaton([r.glob for r in ranked])

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fits = automaton.run(*column_bytes(batch.column(3)))
            best = pa.array(np.where(fits.any(1), fits.argmax(1), len(ranked)))
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], names.take(best), verdicts.take(best)], ["key", "host", "path", "rule", "verdict"])

    host, path = host_and_path(url)
    kind = df.schema[key].dataType.simpleString()
    rows = df.select(F.col(key).alias("key"), host.alias("host"), path.alias("path")).withColumn("canonical", F.concat(F.lit("."), "host", F.lit(SEPARATOR), "path"))
    return rows.mapInArrow(judge, f"key {kind}, host string, path string, rule string, verdict string").withColumnRenamed("key", key)


#: Fixed values of the contract, longest match wins.
CONTRACT_RULES = [
    prefix_rule("allow", "com/"),
    prefix_rule("block", "example.com/en/"),
    prefix_rule("allow", "www.example.com/en/"),
    prefix_rule("block", "net/es/"),
    prefix_rule("block", "net/fr/"),
]
#: Our own wildcard rules, for pages that no rule above fits.
DEFAULT_RULES = [
    UrlRule(None, "*", "*/wp-admin/*", "block"),
    UrlRule(None, "*", "*.exe", "block"),
    UrlRule(None, "*", "*.zip", "block"),
    UrlRule(None, "*", "*/login*", "block"),
]
