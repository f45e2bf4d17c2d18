"""Quality rules as a learned decision list.

Statistics of every text feed sequential covering: grow a conjunction of
thresholds by information gain on two thirds of the labelled rows, prune it
on the rest, keep it if the held rows bear it out, remove what it covers and
go on.  The list becomes one ordered Spark conditional expression.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from arcfield.deploy import ship

SYMBOLS = "#*$%&|<>"
SPACE = " \t\n\x0b\x0c\r"
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_upper", "n_marks", "n_digits")
#: Columns a rule may test, as SQL over STATS; each is 0 for a text without words.
RATIOS = {
    "symbol_ratio": "n_symbols / greatest(n_words, 1)",
    "repeat_ratio": "n_repeat_words / greatest(n_words, 1)",
    "upper_ratio": "n_upper / greatest(word_chars, 1)",
    "mark_ratio": "n_marks / greatest(n_words, 1)",
    "digit_ratio": "n_digits / greatest(word_chars, 1)",
    "dup_line_ratio": "n_dup_lines / greatest(n_words, 1)",
    "word_length": "word_chars / greatest(n_words, 1)",
}
#: Most labelled rows that the learner takes; the choice is by hash of the id.
MAX_LABELLED = 20_000


def repeated_words(words: list, width: int = 3) -> int:
    """Words that lie in a window of ``width`` words found twice or more."""
    n = len(words)
    if n <= width:
        return 0
    seen: dict = {}
    code = np.fromiter((seen.setdefault(w, len(seen)) for w in words), np.int64, n)
    window = code[: n - width + 1]
    for k in range(1, width):
        window = np.unique(window, return_inverse=True)[1] * np.int64(len(seen)) + code[k : n - width + 1 + k] if k > 1 else window * np.int64(len(seen)) + code[k : n - width + 1 + k]
    _, back, count = np.unique(window, return_inverse=True, return_counts=True)
    cover = np.zeros(n + 1, np.int64)
    at = np.flatnonzero(count[back] > 1)
    np.add.at(cover, at, 1)
    np.add.at(cover, at + width, -1)
    return int((np.cumsum(cover[:n]) > 0).sum())


_UPPER, _MARKS, _DIGITS = re.compile(r"[A-ZÀ-ÖØ-Þ]"), re.compile(r"[!?]{2,}|\|"), re.compile(r"[0-9]")


def text_stats(text: str | None) -> tuple[int, ...]:
    text = text or ""
    words = text.encode("utf-8", "surrogatepass").split()
    dup = 0
    if "\n" in text:
        lines = [line for line in text.split("\n") if line.strip(SPACE)]
        dup = len(lines) - len(set(lines))
    chars = len(text) - sum(map(text.count, SPACE))
    return len(words), chars, sum(map(text.count, SYMBOLS)), dup, repeated_words(words), len(_UPPER.findall(text)), len(_MARKS.findall(text)), len(_DIGITS.findall(text))


def with_stats(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with a struct column ``__stats`` of STATS (a null text has no words)."""
    ship(docs.sparkSession)

    @F.pandas_udf(", ".join(f"{c} long" for c in STATS))
    def stats(texts: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([text_stats(t) for t in texts], columns=list(STATS), dtype="int64")

    return docs.withColumn("__stats", stats(F.col(text)))


@dataclass(frozen=True)
class Rule:
    """A conjunction of (column, '>=' or '<=', threshold)."""

    tests: tuple[tuple[str, str, float], ...]

    def mask(self, x: dict[str, np.ndarray]) -> np.ndarray:
        out = np.ones(len(next(iter(x.values()))), bool)
        for name, op, t in self.tests:
            out &= x[name] >= t if op == ">=" else x[name] <= t
        return out

    def column(self) -> Column:
        return F.expr(" and ".join(f"({RATIOS[name]}) {op} {t!r}D" for name, op, t in self.tests) or "true")


def _gain(p: int, n: int, p0: int, n0: int) -> float:
    return p * (np.log2(p / (p + n)) - np.log2(p0 / (p0 + n0))) if p else -1.0


def _grow(x: dict[str, np.ndarray], y: np.ndarray, most: int) -> Rule:
    tests, at = [], np.ones(len(y), bool)
    while len(tests) < most and (at & ~y).any():
        p0, n0, best = int((at & y).sum()), int((at & ~y).sum()), (0.0, None)
        for name in sorted(x):
            v = x[name][at]
            edges = np.unique(np.quantile(v, np.linspace(0, 1, 65)))
            for t in (edges[1:] + edges[:-1]) / 2:
                for op in (">=", "<="):
                    hit = v >= t if op == ">=" else v <= t
                    p = int((hit & y[at]).sum())
                    g = _gain(p, int(hit.sum()) - p, p0, n0)
                    if g > best[0]:
                        best = (g, (name, op, float(round(t, 6))))
        if best[1] is None:
            break
        tests.append(best[1])
        at = Rule(tuple(tests)).mask(x)
    return Rule(tuple(tests))


def _prune(rule: Rule, x: dict[str, np.ndarray], y: np.ndarray) -> Rule:
    def worth(r: Rule) -> float:
        m = r.mask(x)
        p = int((m & y).sum())
        return (2 * p - int(m.sum())) / max(1, int(m.sum()))

    best = rule
    while len(best.tests) > 1:
        shorter = max((Rule(best.tests[:i] + best.tests[i + 1 :]) for i in range(len(best.tests))), key=worth)
        if worth(shorter) < worth(best):
            break
        best = shorter
    return best


def learn(x: dict[str, np.ndarray], rejected: np.ndarray, fold: np.ndarray, *, precision: float = 0.98, least: int = 5, most_rules: int = 16, most_tests: int = 4) -> list[Rule]:
    """Ordered rules for ``rejected``; ``fold`` in 0..2, fold 2 prunes and judges.

    A rule stays only if it is right on ``precision`` of the rows it covers,
    of both parts, and covers ``least`` rows; anything else is kept.
    """
    left, rules = np.ones(len(rejected), bool), []
    while len(rules) < most_rules:
        part = lambda m: ({k: v[m] for k, v in x.items()}, rejected[m])
        grow, held = left & (fold < 2), left & (fold == 2)
        if (rejected & grow).sum() < least or not (rejected & held).any():
            break
        rule = _prune(_grow(*part(grow), most_tests), *part(held))
        m = rule.mask(x) & left
        if not rule.tests or m.sum() < least or (m & rejected).sum() < precision * m.sum():
            break
        rules.append(rule)
        left &= ~m
    return rules


def labelled_stats(docs: DataFrame, labels: DataFrame, limit: int = MAX_LABELLED) -> DataFrame:
    """Statistics of at most ``limit`` labelled documents; only the chosen ids are broadcast."""
    chosen = labels.where("quality is not null and doc_id is not null").groupBy(F.col("doc_id").alias("__id")).agg(F.min("quality").alias("__quality"))
    chosen = chosen.orderBy(F.xxhash64("__id"), "__id").limit(limit)
    found = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("__id"))
    return with_stats(found).select("doc_id", "__quality", "__stats.*")


def learn_rules(docs: DataFrame, labels: DataFrame, limit: int = MAX_LABELLED) -> list[Rule]:
    rows = labelled_stats(docs, labels, limit).select(F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(3)).alias("fold"), "__quality", *[F.expr(f"double({sql})").alias(name) for name, sql in RATIOS.items()], "doc_id").toPandas()
    rows = rows.sort_values("doc_id", kind="stable")
    if not len(rows):
        return []
    return learn({k: rows[k].to_numpy(float) for k in RATIOS}, (rows["__quality"] == 0).to_numpy(), rows["fold"].to_numpy())


def verdict(rules: list[Rule]) -> Column:
    """The ordered conditional: false at the first rule that holds, else true."""
    out = None
    for rule in rules:
        out = F.when(rule.column(), F.lit(False)) if out is None else out.when(rule.column(), F.lit(False))
    return F.lit(True) if out is None else out.otherwise(F.lit(True))


def judge(docs: DataFrame, labels: DataFrame, rules: list[Rule] | None = None) -> DataFrame:
    """``docs`` with STATS, base_failed and kept.

    A null or empty text has no words and fails the base; repeated rows get a
    row each; without labels the list is empty and the base decides alone.
    Columns of ``docs`` that share a name with the added ones are replaced.
    """
    rules = learn_rules(docs, labels) if rules is None else rules
    rest = [c for c in docs.columns if c not in (*STATS, "base_failed", "kept", "__stats")]
    found = with_stats(docs).select(*rest, "__stats.*")
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return found.withColumn("base_failed", failed).withColumn("kept", ~F.col("base_failed") & verdict(rules))


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    out = judge(docs.select("doc_id", "text"), labels)
    return out.select("doc_id", *STATS[:5], "base_failed", "kept")
