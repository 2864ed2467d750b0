"""Quality rules: a decision list learned by sequential covering, as Spark expressions.

Documents are described by counts and shares that Spark computes from their text.
Rules are conjunctions of thresholds.  Each is grown literal by literal for the most
information gain on one part of the labelled rows, pruned on the other part, and kept
if it is precise enough there; rows that it covers leave the training set, and the
next rule is grown on the rest.  All statistics are grouped counts by feature and bin;
the driver sees only those (features times bins) and chooses.  The result is a list of
conditions, applied in order as one conditional expression.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .frames import Workspace, fresh

_SPACE = r"[\x20\x09-\x0D]"
#: Features that rules may test.
FEATURES = ("n_words", "mean_word_chars", "symbol_share", "dup_line_share", "repeat_word_share", "letter_share", "distinct_word_share", "word_share")


def text_statistics(df: DataFrame, text_col: str = "text") -> DataFrame:
    """Adds n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and what the features need.

    Words are runs of characters outside 0x20 and 0x09-0x0D.  Null texts count as
    empty; every count is then zero.  Counts are of code points.  Columns of the output
    names are replaced, others kept.
    """
    TEXT, WORDS, LINES, HASHES, WINDOWS, ORDERED, TWICE = steps = fresh(df, "whole", "words", "lines", "word_hashes", "windows", "sorted_windows", "repeated")
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    step = df.withColumns({TEXT: text})
    step = step.withColumns({WORDS: F.filter(F.split(TEXT, f"{_SPACE}+"), lambda w: w != ""), LINES: F.filter(F.split(TEXT, "\n"), lambda x: F.length(F.translate(x, " \t\n\x0b\f\r", "")) > 0)})
    step = step.withColumn(HASHES, F.transform(WORDS, lambda w: F.xxhash64(w)))
    n = F.size(WORDS)
    windows = F.transform(F.slice(HASHES, F.lit(1), F.greatest(n - 2, F.lit(0))), lambda h, i: F.xxhash64(h, F.get(HASHES, i + 1), F.get(HASHES, i + 2)))
    step = step.withColumn(WINDOWS, windows)
    # positions of windows found twice or more: neighbours in sorted order are equal
    ordered = F.sort_array(F.transform(WINDOWS, lambda g, i: F.struct(g.alias("g"), i.alias("i"))))
    step = step.withColumn(ORDERED, F.when(F.size(F.array_distinct(WINDOWS)) < F.size(WINDOWS), ordered))
    twice = F.filter(ORDERED, lambda x, i: (i > 0) & (F.get(ORDERED, i - 1)["g"] == x["g"]) | F.coalesce(F.get(ORDERED, i + 1)["g"] == x["g"], F.lit(False)))
    step = step.withColumn(TWICE, F.sort_array(F.transform(twice, lambda x: x["i"])))
    start = F.struct(F.lit(0).alias("n"), F.lit(-3).alias("last"))
    covered = F.aggregate(TWICE, start, lambda a, p: F.struct((a["n"] + F.least(F.lit(3), p - a["last"])).alias("n"), p.alias("last")), lambda a: a["n"])
    whole = F.array_join(WORDS, "")
    step = step.withColumns(
        {
            "n_words": n.cast("long"),
            "word_chars": F.length(whole).cast("long"),
            "n_symbols": F.regexp_count(TEXT, F.lit(r"[#*$%&|<>]")).cast("long"),
            "n_dup_lines": (F.size(LINES) - F.size(F.array_distinct(LINES))).cast("long"),
            "n_repeat_words": F.coalesce(covered, F.lit(0)).cast("long"),
            "n_lines": F.size(LINES).cast("long"),
            "n_letters": F.regexp_count(TEXT, F.lit(r"\p{L}")).cast("long"),
            "n_distinct_words": F.size(F.array_distinct(HASHES)).cast("long"),
            "n_chars": F.length(TEXT).cast("long"),
        }
    )
    return step.drop(*steps)


def features() -> dict[str, Column]:
    """The features as expressions over text_statistics; shares of nothing are zero."""
    share = lambda a, b: F.coalesce(F.try_divide(F.col(a).cast("double"), F.col(b)), F.lit(0.0))
    return {
        "n_words": F.col("n_words").cast("double"),
        "mean_word_chars": share("word_chars", "n_words"),
        "symbol_share": share("n_symbols", "word_chars"),
        "dup_line_share": share("n_dup_lines", "n_lines"),
        "repeat_word_share": share("n_repeat_words", "n_words"),
        "letter_share": share("n_letters", "n_chars"),
        "distinct_word_share": share("n_distinct_words", "n_words"),
        "word_share": share("word_chars", "n_chars"),
    }


@dataclass(frozen=True)
class Literal:
    feature: str
    above: bool  # feature > threshold, else feature <= threshold
    threshold: float

    def __str__(self) -> str:
        return f"{self.feature} {'>' if self.above else '<='} {self.threshold!r}"


@dataclass(frozen=True)
class DecisionList:
    """Rules in order; the first that holds gives the verdict, else ``default``."""

    rules: tuple[tuple[tuple[Literal, ...], bool], ...]
    default: bool = True

    def condition(self, literals: tuple[Literal, ...]) -> Column:
        own, out = features(), F.lit(True)
        for x in literals:
            out = out & (own[x.feature] > F.lit(x.threshold) if x.above else own[x.feature] <= F.lit(x.threshold))
        return out

    def verdict(self) -> Column:
        """True where a document is kept, as one conditional expression."""
        out: Column | None = None
        for literals, kept in self.rules:
            out = F.when(self.condition(literals), F.lit(kept)) if out is None else out.when(self.condition(literals), F.lit(kept))
        return F.lit(self.default) if out is None else out.otherwise(F.lit(self.default))

    def __str__(self) -> str:
        lines = [f"{'keep' if k else 'drop'} if {' and '.join(map(str, x))}" for x, k in self.rules]
        return "\n".join([*lines, f"{'keep' if self.default else 'drop'} otherwise"])


def _gain(p: float, n: float, p0: float, n0: float) -> float:
    """Information gain of going from p0 to p positives among p + n."""
    return p * (math.log2((p + 1e-9) / (p + n + 1e-9)) - math.log2((p0 + 1e-9) / (p0 + n0 + 1e-9))) if p else 0.0


def learn_rules(statistics: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", label_col: str = "quality", bins: int = 32, most_rules: int = 6, most_literals: int = 3, least_rows: int = 5, precision: float = 0.8) -> DecisionList:
    """A list of rules for low quality (label 0) from the statistics of labelled documents.

    Two rows of three (by a hash of the id) grow rules, the third prunes them; where
    the pruning part is empty the growing part stands in.  Of several labels of an id
    the largest holds; null ids and labels teach nothing.  Without labelled rows of
    both kinds the list has no rule and keeps everything.
    """
    work = Workspace(statistics.sparkSession, "quality-rules")
    told = labels.where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg((F.max(label_col) <= 0).alias("bad"))
    rows = statistics.join(told, F.col(id_col) == F.col("id")).select("id", "bad", *[c.alias(n) for n, c in features().items()])
    rows = work.keep(rows, "labelled")
    cuts_row = rows.agg(F.sum(F.col("bad").cast("int")).alias("bad"), F.count(F.lit(1)).alias("n"), *[F.percentile_approx(f, [k / bins for k in range(1, bins)], 2000).alias(f) for f in FEATURES]).first()
    if not cuts_row["n"] or not cuts_row["bad"] or cuts_row["bad"] == cuts_row["n"]:
        return DecisionList(())
    cuts = {f: sorted(set(cuts_row[f])) for f in FEATURES}
    at = lambda f: F.size(F.filter(F.array(*[F.lit(c) for c in cuts[f]]), lambda c: c < F.col(f)))
    binned = work.keep(rows.select("bad", (F.pmod(F.xxhash64("id"), F.lit(3)) == 2).alias("prune"), *[at(f).cast("int").alias(f) for f in FEATURES]).groupBy("bad", "prune", *FEATURES).agg(F.count(F.lit(1)).alias("k")), "binned")

    def holds(literals) -> Column:
        out = F.lit(True)
        for x in literals:
            bin_at = cuts[x.feature].index(x.threshold)  # value > cuts[i] exactly if more than i cuts lie below it
            out = out & (F.col(x.feature) > bin_at if x.above else F.col(x.feature) <= bin_at)
        return out

    def totals(part: DataFrame, *conditions: Column) -> list[tuple[float, float]]:
        sums = [F.sum(F.when(c & (F.col("bad") == b), F.col("k")).otherwise(0)) for c in conditions for b in (True, False)]
        r = part.agg(*[x.alias(f"s{i}") for i, x in enumerate(sums)]).first()
        return [(float(r[2 * i] or 0), float(r[2 * i + 1] or 0)) for i in range(len(conditions))]

    def histogram(part: DataFrame) -> dict[tuple[str, int], list[float]]:
        """Bad and good rows by feature and bin: features * bins * 2 rows at most."""
        long = part.select("bad", "k", F.explode(F.array(*[F.struct(F.lit(f).alias("f"), F.col(f).alias("b")) for f in FEATURES])).alias("x"))
        out: dict[tuple[str, int], list[float]] = {}
        for r in long.groupBy("x.f", "x.b", "bad").agg(F.sum("k").alias("k")).collect():
            out.setdefault((r["f"], r["b"]), [0.0, 0.0])[0 if r["bad"] else 1] += r["k"]
        return out

    rules: list[tuple[tuple[Literal, ...], bool]] = []
    left = F.lit(True)
    while len(rules) < most_rules:
        growing = binned.where(~F.col("prune") & left)
        literals: list[Literal] = []
        while len(literals) < most_literals:
            counts = histogram(growing.where(holds(literals)))
            p0 = sum(v[0] for (f, _), v in counts.items() if f == FEATURES[0])
            n0 = sum(v[1] for (f, _), v in counts.items() if f == FEATURES[0])
            best = (0.0, None)
            for f in FEATURES:
                below = [0.0, 0.0]
                for b, cut in enumerate(cuts[f]):
                    here = counts.get((f, b), (0.0, 0.0))
                    below = [below[0] + here[0], below[1] + here[1]]
                    for above in (False, True):
                        p, n = (p0 - below[0], n0 - below[1]) if above else below
                        gain = _gain(p, n, p0, n0)
                        if p >= least_rows and gain > best[0] + 1e-9:
                            best = (gain, Literal(f, above, cut))
            if best[1] is None or best[1] in literals:
                break
            literals.append(best[1])
            if not n0:
                break
        if not literals:
            break
        pruning = binned.where(F.col("prune") & left)
        shown = totals(pruning, *[holds(literals[:k]) for k in range(1, len(literals) + 1)])
        if not any(p + n for p, n in shown):
            shown = totals(growing, *[holds(literals[:k]) for k in range(1, len(literals) + 1)])
        # the shortest prefix with the best Laplace precision
        worth = [((p + 1) / (p + n + 2), -k) for k, (p, n) in enumerate(shown)]
        length = -max(worth)[1] + 1
        p, n = shown[length - 1]
        if p / max(1.0, p + n) < precision or p < 1:
            break
        rule = tuple(literals[:length])
        rules.append((rule, False))
        left = left & ~holds(rule)
    work.forget("labelled", "binned")
    return DecisionList(tuple(rules))


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (F.lit(100) * F.col("n_repeat_words") > F.lit(50) * F.col("n_words"))


def judge(df: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **settings) -> DataFrame:
    """(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept) of every row.

    A row is kept if it passes the base limits and no learned rule drops it.  Null and
    empty texts have no words and fail the limits; texts of any length are counted whole.
    Rows with a null id are judged like the rest; repeated rows get equal verdicts; other
    columns are not read, whatever their names.  An empty table stays empty; without
    labels of both kinds only the limits judge.
    """
    work = Workspace(df.sparkSession, "quality")
    found = work.keep(text_statistics(df.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))).drop("text"), "statistics")
    rules = learn_rules(found, labels.withColumnRenamed(id_col, "doc_id"), **settings)
    failed = base_failed()
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), F.when(failed, F.lit(False)).otherwise(rules.verdict()).alias("kept"))
