"""Operator 5: learned decision lists as quality rules, native.

Statistics of each text are DataFrame expressions only. From the statistics of labelled rows (at most `most_rows`, the
smallest by hash of doc_id, of the learning fold) sequential covering learns an ordered list of rules for rejecting:
a conjunction of thresholds is grown by information gain on two thirds of the rows, pruned on the other third, kept if
it is precise there, and the rows it covers are taken out before the next one. The list becomes one ordered Spark
conditional; the driver sees only the bounded sample of numbers, executors run no Python.

Edge cases: null and empty texts have all counts 0 and fail the base rules; texts of any length are taken whole, in
n log n; repeated rows are judged each; without labels of both kinds the list is empty and keeps what passes the base;
columns of the input other than doc_id and text are not touched and may have any names.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import held_out

MOST_ROWS = 12_000
# What separates words, and the symbols that are counted.
BLANKS = " \t\n\x0b\x0c\r"
WORD_GAPS = r"[\x20\x09-\x0D]+"
SYMBOLS = "#*$%&|<>"
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
FEATURES = ("mean_word", "symbol_share", "upper_share", "mark_share", "repeat_share", "distinct_share", "dup_line_share", "digit_share", "letter_share")


def without(text: Column, characters: str) -> Column:
    return F.translate(text, characters, "")


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """`body` of a value that is computed once, also where the optimizer moves the whole expression elsewhere."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def repeated_words(words: Column) -> Column:
    """How many words lie in a window of three that occurs twice or more: windows are sorted by hash, neighbours compared."""
    last = F.size(words) - 3
    windows = F.transform(F.sequence(F.lit(0), last), lambda i: F.struct(F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)).alias("h"), i.alias("i")))

    def places(s: Column) -> Column:
        shared = F.transform(s, lambda x, k: F.when((F.when(k > 0, F.get(s, k - 1)["h"]) == x["h"]) | (F.get(s, k + 1)["h"] == x["h"]), x["i"]))
        return F.sort_array(F.filter(shared, lambda i: i.isNotNull()))

    def covered(p: Column) -> Column:
        start = F.struct(F.lit(-3).alias("last"), F.lit(0).cast("long").alias("sum"))
        return F.aggregate(p, start, lambda a, i: F.struct(i.alias("last"), (a["sum"] + F.least(F.lit(3), i - a["last"])).alias("sum")))["sum"]

    return F.when(last >= 0, let(let(F.sort_array(windows), places), covered))


def statistics(docs: DataFrame, carried: Sequence[str] = ()) -> DataFrame:
    """doc_id, the five counts and the features of every text; `carried` columns come along in the struct _row."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    row = [F.struct(*carried).alias("_row")] if carried else []
    along = ["_row"] if carried else []
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("_t"), *row)
    rows = rows.withColumn("_w", F.filter(F.split("_t", WORD_GAPS), lambda w: w != ""))
    n, covered = F.size("_w"), let(F.col("_w"), repeated_words)
    rows = rows.withColumn("_l", F.filter(F.split("_t", "\n"), lambda x: without(x, BLANKS) != ""))
    bare = without(F.col("_t"), BLANKS)
    rows = rows.select(
        "doc_id", *along, n.cast("long").alias("n_words"), F.char_length(bare).cast("long").alias("word_chars"),
        (F.char_length("_t") - F.char_length(without(F.col("_t"), SYMBOLS))).cast("long").alias("n_symbols"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"), F.coalesce(covered, F.lit(0)).cast("long").alias("n_repeat_words"),
        F.size("_l").alias("_lines"), F.size(F.array_distinct("_w")).alias("_distinct"),
        F.char_length(F.regexp_replace(bare, r"[^\p{Lu}]+", "")).alias("_upper"), F.char_length(F.regexp_replace(bare, r"[^\p{L}]+", "")).alias("_letters"),
        (F.char_length("_t") - F.char_length(without(F.col("_t"), "!?"))).alias("_marks"), (F.char_length("_t") - F.char_length(without(F.col("_t"), "0123456789"))).alias("_digits"),
    )

    def share(a: str, b: str) -> Column:
        return F.coalesce(F.try_divide(F.col(a).cast("double"), F.col(b)), F.lit(0.0))

    return rows.select(
        "doc_id", *along, *COUNTS, share("word_chars", "n_words").alias("mean_word"), share("n_symbols", "word_chars").alias("symbol_share"), share("_upper", "_letters").alias("upper_share"),
        share("_marks", "n_words").alias("mark_share"), share("n_repeat_words", "n_words").alias("repeat_share"), share("_distinct", "n_words").alias("distinct_share"),
        share("n_dup_lines", "_lines").alias("dup_line_share"), share("_digits", "word_chars").alias("digit_share"), share("_letters", "word_chars").alias("letter_share"),
    )


@dataclass(frozen=True)
class Condition:
    feature: str
    above: bool
    threshold: float

    def holds(self, row: dict[str, float]) -> bool:
        return row[self.feature] > self.threshold if self.above else row[self.feature] <= self.threshold

    def sql(self) -> str:
        return f"{self.feature} {'>' if self.above else '<='} {self.threshold!r}D"


@dataclass(frozen=True)
class Rule:
    """Reject where all conditions hold."""

    conditions: tuple[Condition, ...]

    def holds(self, row: dict[str, float]) -> bool:
        return all(c.holds(row) for c in self.conditions)

    def sql(self) -> str:
        return " AND ".join(c.sql() for c in self.conditions)


Labelled = tuple[dict[str, float], int]


def cuts(rows: Sequence[Labelled], feature: str, most: int = 48) -> list[float]:
    """Midpoints between neighbouring values at even ranks."""
    values = sorted({x[feature] for x, _ in rows})
    step = max(1, len(values) // most)
    return [(values[i] + values[i + 1]) / 2 for i in range(0, len(values) - 1, step)]


def grow(rows: Sequence[Labelled], features: Sequence[str], most_conditions: int) -> list[Condition]:
    """Add the condition of the largest information gain until no kept row is covered."""
    chosen: list[Condition] = []
    covered = list(rows)
    while len(chosen) < most_conditions:
        bad = sum(y for _, y in covered)
        if not bad or bad == len(covered):
            break
        base, best = math.log2(bad / len(covered)), (1e-9, None)
        for f in features:
            pairs = sorted((x[f], y) for x, y in covered)
            limits, i, below_bad = cuts(covered, f), 0, 0
            for t in limits:
                while i < len(pairs) and pairs[i][0] <= t:
                    below_bad += pairs[i][1]
                    i += 1
                for above, p, total in ((False, below_bad, i), (True, bad - below_bad, len(pairs) - i)):
                    if p and (gain := p * (math.log2(p / total) - base)) > best[0]:
                        best = (gain, Condition(f, above, t))
        if best[1] is None:
            break
        chosen.append(best[1])
        covered = [r for r in covered if best[1].holds(r[0])]
    return chosen


def worth(conditions: Sequence[Condition], rows: Sequence[Labelled]) -> tuple[float, int, int]:
    hit = [y for x, y in rows if all(c.holds(x) for c in conditions)]
    bad = sum(hit)
    return (2 * bad - len(hit)) / max(1, len(hit)), bad, len(hit)


def learn_rules(rows: Sequence[Labelled], features: Sequence[str] = FEATURES, precision: float = 0.97, least_hits: int = 3, most_rules: int = 16, most_conditions: int = 4) -> list[Rule]:
    """Sequential covering over (statistics, 1 if to be rejected) rows, in the order given."""
    left, rules = list(rows), []
    while len(rules) < most_rules:
        growing = [r for i, r in enumerate(left) if i % 3]
        pruning = [r for i, r in enumerate(left) if i % 3 == 0]
        conditions = grow(growing, features, most_conditions)
        while len(conditions) > 1 and worth(conditions[:-1], pruning)[0] >= worth(conditions, pruning)[0]:
            conditions = conditions[:-1]
        if not conditions:
            break
        for sample in (pruning, growing):
            _, bad, hits = worth(conditions, sample)
            if bad < precision * hits or bad < least_hits:
                return rules
        rules.append(Rule(tuple(conditions)))
        left = [r for r in left if not rules[-1].holds(r[0])]
    return rules


def verdict(rules: Sequence[Rule]) -> Column:
    """The list as one ordered conditional: true keeps."""
    if not rules:
        return F.lit(True)
    out = F
    for rule in rules:
        out = out.when(F.expr(rule.sql()), F.lit(False))
    return out.otherwise(F.lit(True))


def fit(docs: DataFrame, labels: DataFrame, most_rows: int = MOST_ROWS) -> list[Rule]:
    """Rules from labelled statistics (labels: doc_id, quality 0 or 1) of at most `most_rows` rows of the learning fold."""
    known = labels.where("doc_id is not null and quality is not null").where(~held_out("doc_id")).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    sample = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most_rows)
    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(sample), "doc_id")
    rows = statistics(chosen.select("doc_id", "text")).join(F.broadcast(sample), "doc_id").select("doc_id", "quality", base_failed().alias("failed"), *FEATURES)
    one = rows.groupBy("doc_id", "quality").agg(F.min(F.struct("failed", *FEATURES)).alias("x")).select("doc_id", "quality", "x.*")  # bounded whatever is repeated
    got = sorted(one.collect(), key=lambda r: (r.doc_id * 2654435761 % (1 << 32), r))
    return learn_rules([({f: r[f] for f in FEATURES}, 1 - int(r.quality)) for r in got if not r.failed])


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def judge(docs: DataFrame, rules: Sequence[Rule]) -> DataFrame:
    """doc_id, the counts, base_failed and kept for every document; rule is the place of the rule that rejects."""
    rows = statistics(docs)
    which = F.coalesce(*(F.when(F.expr(r.sql()), F.lit(i)) for i, r in enumerate(rules)), F.lit(None).cast("int"))
    return rows.select("doc_id", *COUNTS, base_failed().alias("base_failed"), (~base_failed() & verdict(rules)).alias("kept"), which.alias("rule"))


def keep(docs: DataFrame, rules: Sequence[Rule], columns: Sequence[str]) -> DataFrame:
    """The given columns of the documents that are kept; each row is judged by itself."""
    judged = statistics(docs, columns).select("_row", (~base_failed() & verdict(rules)).alias("_kept"))
    return judged.select(F.inline(F.when(F.col("_kept"), F.array("_row"))))
