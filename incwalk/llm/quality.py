"""Quality rules as learned decision lists, in DataFrame functions only.

Statistics of a text are native expressions. Sequential covering grows conjunctions of thresholds
on them from labelled rows, prunes each on rows it was not grown on, and takes the covered rows
away; the list comes out as one ordered CASE expression, so applying it is a map over the scan.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from incwalk.llm.common import GAP_CHARS, GAP_CLASS

SYMBOLS = "#*$%&|<>"
#: Labelled rows that a list is learned from, at most; those of least hash are taken.
LABELLED = 20_000
FEATURES = ("n_words", "mean_word", "symbols", "dup_lines", "repeats", "capitals", "bangs", "distinct_words")


def _count(text: Column, chars: str) -> Column:
    return (F.length(text) - F.length(F.translate(text, chars, ""))).cast("long")


def text_statistics(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Adds ``n_words``, ``word_chars``, ``n_symbols``, ``n_dup_lines``, ``n_repeat_words`` and the shares in ``FEATURES``.

    A null text counts as one without words: all statistics are 0. Columns of these names are replaced.
    """
    own = ("__text", "__words", "__tri", "__lines", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", *FEATURES)
    keep = [c for c in docs.columns if c not in own]
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    a = docs.select(*keep, text.alias("__text"))
    trimmed = F.btrim("__text", F.lit(GAP_CHARS))
    worded = F.filter(F.split("__text", "\n"), lambda x: F.btrim(x, F.lit(GAP_CHARS)) != "")
    b = a.select("*", F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, GAP_CLASS)).alias("__words"), worded.alias("__lines"))
    n = F.size("__words")
    tri = F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(F.get("__words", i), F.get("__words", i + 1), F.get("__words", i + 2)))
    c = b.select("*", F.when(n >= 3, tri).otherwise(F.array().cast("array<long>")).alias("__tri"))
    paired = F.array_sort(F.transform("__tri", lambda x, i: F.struct(x.alias("h"), i.alias("i"))))

    def covered(p: Column) -> Column:
        """Where some window repeats: its places, neighbours once sorted by hash, and the words they cover."""
        at = F.filter(F.transform(p, lambda x, j: F.when((x["h"] == F.get(p, j - 1)["h"]) | (x["h"] == F.get(p, j + 1)["h"]), x["i"])), lambda x: x.isNotNull())
        start = F.struct(F.lit(-3).alias("last"), F.lit(0).cast("long").alias("sum"))
        return F.aggregate(F.array_sort(at), start, lambda acc, x: F.struct(x.alias("last"), (acc["sum"] + F.least(F.lit(3), x - acc["last"])).alias("sum")), lambda acc: acc["sum"])

    # a one-element array binds the sorted places to a name, so that they are sorted once
    repeated = F.when(F.size(F.array_distinct("__tri")) == F.size("__tri"), F.lit(0).cast("long")).otherwise(F.element_at(F.transform(F.array(paired), covered), 1))
    d = c.select(
        *keep,
        n.cast("long").alias("n_words"),
        (F.length("__text") - _count(F.col("__text"), GAP_CHARS)).cast("long").alias("word_chars"),
        _count(F.col("__text"), SYMBOLS).alias("n_symbols"),
        (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("long").alias("n_dup_lines"),
        repeated.alias("n_repeat_words"),
        F.size("__lines").alias("__n_lines"),
        F.size(F.array_distinct("__words")).alias("__n_distinct"),
        _count(F.col("__text"), "ABCDEFGHIJKLMNOPQRSTUVWXYZ").alias("__n_upper"),
        _count(F.col("__text"), "!?").alias("__n_bangs"),
    )
    chars, words = F.greatest(F.col("word_chars"), F.lit(1)), F.greatest(F.col("n_words"), F.lit(1))
    return d.select(
        *keep, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        (F.col("word_chars") / words).alias("mean_word"),
        (F.col("n_symbols") / chars).alias("symbols"),
        (F.col("n_dup_lines") / F.greatest(F.col("__n_lines"), F.lit(1))).alias("dup_lines"),
        (F.col("n_repeat_words") / words).alias("repeats"),
        (F.col("__n_upper") / chars).alias("capitals"),
        (F.col("__n_bangs") / chars).alias("bangs"),
        (F.col("__n_distinct") / words).alias("distinct_words"),
    )


@dataclass(frozen=True)
class Condition:
    feature: str
    above: bool
    threshold: float

    def column(self) -> Column:
        return F.col(self.feature) > F.lit(self.threshold) if self.above else F.col(self.feature) <= F.lit(self.threshold)

    def holds(self, x: dict[str, np.ndarray]) -> np.ndarray:
        return x[self.feature] > self.threshold if self.above else x[self.feature] <= self.threshold


@dataclass(frozen=True)
class Rule:
    """Rejects where all conditions hold."""

    conditions: tuple[Condition, ...]

    def column(self) -> Column:
        out = F.lit(True)
        for c in self.conditions:
            out = out & c.column()
        return out

    def holds(self, x: dict[str, np.ndarray], n: int) -> np.ndarray:
        out = np.ones(n, bool)
        for c in self.conditions:
            out &= c.holds(x)
        return out


def labelled_sample(docs: DataFrame, labels: DataFrame, label_col: str = "quality", most: int = LABELLED) -> DataFrame:
    """At most ``most`` labelled ids, by hash; their number bounds the broadcast that picks their texts."""
    ids = labels.where(F.col("doc_id").isNotNull() & F.col(label_col).isNotNull()).groupBy("doc_id").agg(F.min(label_col).alias("__label"))
    return docs.join(F.broadcast(ids.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)), "doc_id")


def learn_list(docs: DataFrame, labels: DataFrame, label_col: str = "quality", most_rules: int = 12, most_conditions: int = 3, precision: float = 0.9) -> list[Rule]:
    """Rules that reject label 0. Without labelled rows of both kinds the list is empty and rejects nothing."""
    sample = text_statistics(labelled_sample(docs.select("doc_id", "text"), labels, label_col).select("doc_id", "text", "__label"))
    got = sample.select("doc_id", "__label", *FEATURES).collect()
    if not got:
        return []
    got.sort(key=lambda r: (r["doc_id"], *(r[f] for f in FEATURES)))
    x = {f: np.array([r[f] for r in got], float) for f in FEATURES}
    bad = np.array([r["__label"] == 0 for r in got])
    grow_part = np.array([zlib.crc32(str(r["doc_id"]).encode()) % 3 != 2 for r in got])  # by hash: labels may follow the ids
    return _cover(x, bad, grow_part, most_rules, most_conditions, precision)


def _cover(x, bad, grow_part, most_rules, most_conditions, precision) -> list[Rule]:
    left, rules, n = np.ones(len(bad), bool), [], len(bad)
    while len(rules) < most_rules and (left & bad & grow_part).sum() >= 5:
        inside, conditions = left & grow_part, []
        while len(conditions) < most_conditions:
            p0, n0 = (inside & bad).sum(), (inside & ~bad).sum()
            if not p0 or not n0:
                break
            best = (0.0, None)
            base = np.log2(p0 / (p0 + n0))
            for f in FEATURES:
                v = np.sort(x[f][inside])
                own = np.sort(x[f][inside & bad])
                cuts = {float(a[int(q * (len(a) - 1))]) for a in (v, own) for q in (0, 0.005, 0.01, 0.02, 0.05, 0.1, 0.25, 0.5, 0.75, 0.9, 0.95, 0.98, 0.99, 0.995)}
                for t in sorted(cuts):
                    for above in (True, False):
                        c = Condition(f, above, t)
                        on = inside & c.holds(x)
                        p1, n1 = (on & bad).sum(), (on & ~bad).sum()
                        if p1:
                            gain = p1 * (np.log2(p1 / (p1 + n1)) - base)
                            if gain > best[0] + 1e-9:
                                best = (gain, c)
            if best[1] is None:
                break
            c = best[1]  # then half way to where the rejected rows begin: near values of kept rows stay kept
            edge = np.quantile(x[c.feature][inside & bad & c.holds(x)], 0.01 if c.above else 0.99)
            c = Condition(c.feature, c.above, float((c.threshold + edge) / 2))
            conditions.append(c)
            inside = inside & c.holds(x)
        # prune: the shortest prefix that does best on the rows it was not grown on
        pruned, worth = None, 0.0
        for k in range(1, len(conditions) + 1):
            on = Rule(tuple(conditions[:k])).holds(x, n) & left & ~grow_part
            p1, n1 = (on & bad).sum(), (on & ~bad).sum()
            if p1 and p1 / (p1 + n1) >= precision and (p1 - n1) > worth:
                pruned, worth = Rule(tuple(conditions[:k])), p1 - n1
        if pruned is None:
            break
        rules.append(pruned)
        left &= ~pruned.holds(x, n)
    return rules


def list_expression(rules: list[Rule]) -> Column:
    """The list as one ordered CASE: false at the first rule that holds, else true."""
    if not rules:
        return F.lit(True)
    out = F.when(rules[0].column(), F.lit(False))
    for r in rules[1:]:
        out = out.when(r.column(), F.lit(False))
    return out.otherwise(F.lit(True))


def judge(docs: DataFrame, rules: list[Rule], least_words: int = 50, most_repeats: int = 50) -> DataFrame:
    """``docs`` with the statistics, ``base_failed`` and ``kept``. Null or empty texts fail the base. No rows are lost."""
    base = (F.col("n_words") < least_words) | (F.col("n_repeat_words") * 100 > F.col("n_words") * most_repeats)
    return text_statistics(docs).withColumn("base_failed", base).withColumn("kept", ~base & list_expression(rules))


def keep_good(docs: DataFrame, rules: list[Rule], text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that are kept, their columns untouched whatever their names.

    Rows are dropped by exploding an array of one or none. A filter on ``kept`` would be pushed below
    the projections, where every reference to a statistic becomes a copy of its expression, and
    copies of copies take the optimizer minutes.
    """
    row = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("__row"), F.col(f"`{text_col}`").alias("text"))
    one = F.when(F.col("kept"), F.array(F.lit(True))).otherwise(F.array().cast("array<boolean>"))
    return judge(row, rules).select("__row", F.explode(one).alias("__kept")).select("__row.*")
