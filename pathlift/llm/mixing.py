"""Mixing sources to target weights by iterative proportional fitting.

Documents fall into cells by their strata (source, language, topic).  The token weights
of the cells are raked: each pass scales them, one stratum after the other, so that
every value of the stratum gets its target share, until no share is off by more than a
tolerance.  A cell's raked weight is its tokens times one factor for each of its values:
only these factors are carried from step to step, so the cells stay where they are and
a value that holds most cells is summed like any other.  The share of a cell's raked
weight in its tokens, times one factor, is the probability with which its documents are
drawn; the factor is set so that the expected tokens meet the budget with no
probability above one.  A document is drawn if a uniform number made from its id lies
below its probability, so the same rows always give the same sample.
"""

from __future__ import annotations

import math
from collections.abc import Mapping
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from .frames import Workspace, fresh

NONE = "(none)"
#: Tables of values or cells up to this number of rows are broadcast; longer ones are joined by shuffle.
BROADCAST_CELLS = 100_000
#: Factors of a stratum with up to this many values stand in the plan as a literal map; more are a table, written anew in each step.
LITERAL_VALUES = 2_000


def token_count(text_col: str = "text") -> Column:
    """Words of a text: runs of characters outside 0x20 and 0x09-0x0D; zero for null."""
    return F.coalesce(F.regexp_count(F.col(text_col), F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def surface_topic(text_col: str = "text") -> Column:
    """A topic by the surface of a text, where no topic column is given."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    count = lambda mark: F.length(text) - F.length(F.replace(text, F.lit(mark), F.lit("")))
    return (
        F.when(text == "", F.lit("empty"))
        .when(F.lit(40) * count("|") > F.length(text), F.lit("table"))
        .when(F.lit(40) * (count("#") + count("*") + count("$") + count("%") + count("&")) > F.length(text), F.lit("markup"))
        .when(F.lit(40) * count("!") > F.length(text), F.lit("exclaiming"))
        .when(F.length(text) < 400, F.lit("note"))
        .when(F.length(text) < 4000, F.lit("article"))
        .otherwise(F.lit("long read"))
    )


def uniform(id_col: str, text_col: str | None = None) -> Column:
    """A number in [0, 1) from the md5 of the id's decimal text (of the text where the id is null)."""
    key = F.coalesce(F.col(id_col).cast("string"), *([F.col(text_col)] if text_col else []), F.lit(""))
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, 13), 16, 10).cast("double") / F.lit(float(2**52))


@dataclass(frozen=True)
class Raked:
    """Cells (strata, tokens, weight); the passes made; the largest relative gap left between a share and its target."""

    cells: DataFrame
    passes: int
    gap: float


def _small(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_CELLS else df


def rake(cells: DataFrame, strata: list[str], targets: Mapping[str, DataFrame], work: Workspace, *, tolerance: float = 1e-13, most_passes: int = 200) -> Raked:
    """Cells (strata, tokens) with their raked ``weight``.

    ``targets`` has, for each stratum, a frame (value, share); shares of values that
    have no cell are spread over the others, values without a target keep nothing.
    Passes end when no share of the pass was off by more than ``tolerance``, or when
    targets that no weights can meet leave a gap that ``most_passes`` do not close: it
    is returned.
    """
    rows = cells.where("tokens > 0")
    tables, sizes, held = {}, {}, {}
    for s in strata:
        present = rows.select(F.col(s).alias("value")).distinct().join(targets[s].select("value", "share"), "value", "left").fillna(0.0, ["share"])
        all_shares = present.agg(F.sum("share").alias("all"))
        spread = present.crossJoin(F.broadcast(all_shares)).select("value", F.coalesce(F.try_divide("share", "all"), F.lit(0.0)).alias("share"), F.lit(1.0).alias("factor"))  # one row
        tables[s] = work.keep(spread, f"factors-{s}-0")
        sizes[s] = tables[s].count()
        if sizes[s] <= LITERAL_VALUES:
            held[s] = {r["value"]: [r["share"], 1.0] for r in tables[s].collect()}

    def weighed() -> DataFrame:
        out, factors = rows, []
        for s in strata:
            if s in held:
                pairs = [F.lit(x) for value, (_, factor) in held[s].items() for x in (value, factor)]
                factors.append(F.element_at(F.create_map(*pairs), F.col(s)) if pairs else F.lit(1.0))
            else:
                out = out.join(_small(tables[s].select(F.col("value").alias(s), F.col("factor").alias(f"factor of {s}")), sizes[s]), s)
                factors.append(F.col(f"factor of {s}"))
        out = out.withColumn("weight", math.prod(factors, start=F.col("tokens").cast("double")))
        return out.drop(*[f"factor of {s}" for s in strata])

    def stepped(s: str) -> float:
        """Scales the factors of one stratum; returns how far its worst share was off."""
        now = weighed().groupBy(F.col(s).alias("value")).agg(F.sum("weight").alias("now"))
        if s in held:
            worst = 0.0
            for r in now.collect():  # LITERAL_VALUES rows at most
                own = held[s][r["value"]]
                worst = max(worst, abs(r["now"] / own[0] - 1) if own[0] > 0 else 0.0)
                own[1] = own[1] * own[0] / r["now"] if r["now"] > 0 else 0.0
            return worst
        scaled = F.when(F.col("now") > 0, F.col("factor") * F.col("share") / F.col("now")).otherwise(0.0)
        seen = Observation()
        joined = tables[s].join(now, "value", "left").observe(seen, F.max(F.when(F.col("share") > 0, F.abs(F.col("now") / F.col("share") - 1))).alias("off"))
        tables[s] = work.keep(joined.select("value", "share", scaled.alias("factor")), f"factors-{s}-{made}")
        work.forget(f"factors-{s}-{made - 1}")
        return seen.get["off"] or 0.0

    gap, made = math.inf, 0
    while made < most_passes and gap > tolerance:
        made += 1
        gap = max(stepped(s) for s in strata)
    out = work.keep(weighed(), "raked")
    work.forget(*[n for n in work.kept if n.startswith("factors-")])
    return Raked(out, made, gap)


def tempered(cells: DataFrame, stratum: str, exponent: float) -> DataFrame:
    """Target shares (value, share) in proportion to a power of each value's tokens."""
    sums = cells.where("tokens > 0").groupBy(F.col(stratum).alias("value")).agg(F.sum("tokens").alias("n"))
    powers = sums.select("value", F.pow(F.col("n").cast("double"), F.lit(exponent)).alias("p"))
    return powers.crossJoin(F.broadcast(powers.agg(F.sum("p").alias("all")))).select("value", (F.col("p") / F.col("all")).alias("share"))


def calibrated(raked: DataFrame, budget: float, most_rounds: int = 64) -> DataFrame:
    """Raked cells with the ``probability`` of their documents.

    The factor f solves sum(min(tokens, f * weight)) = budget: what full cells cannot
    take is spread over the others until no further cell fills up.  A budget at or
    above all tokens that have weight draws all of them.
    """
    factor = 0.0
    for _ in range(most_rounds):
        full = F.col("weight") * F.lit(factor) >= F.col("tokens")
        r = raked.agg(F.sum(F.when(full, F.col("tokens")).otherwise(0)).alias("full"), F.sum(F.when(full, 0.0).otherwise(F.col("weight"))).alias("open")).first()
        if not r["open"]:
            break
        before, factor = factor, max(0.0, budget - float(r["full"] or 0)) / float(r["open"])
        if abs(factor - before) <= 1e-14 * factor:
            break
    share = F.least(F.lit(1.0), F.col("weight") * F.lit(factor) / F.col("tokens"))
    return raked.withColumn("probability", share)


@dataclass(frozen=True)
class Mixture:
    """Cells with their probabilities, and how far their raking came."""

    strata: tuple[str, ...]
    cells: DataFrame
    passes: int
    gap: float

    def report(self) -> DataFrame:
        """(stratum, value, tokens, share, drawn_share): raked and expected shares by value."""
        parts = [F.struct(F.lit(s).alias("stratum"), F.col(s).alias("value")) for s in self.strata]
        long = self.cells.select(F.explode(F.array(*parts)).alias("p"), "tokens", "weight", (F.col("probability") * F.col("tokens")).alias("drawn"))
        sums = long.groupBy("p.stratum", "p.value").agg(F.sum("tokens").alias("tokens"), F.sum("weight").alias("weight"), F.sum("drawn").alias("drawn"))
        whole = sums.groupBy("stratum").agg(F.sum("weight").alias("all_weight"), F.sum("drawn").alias("all_drawn"))
        return sums.join(F.broadcast(whole), "stratum").select("stratum", "value", "tokens", F.try_divide("weight", "all_weight").alias("share"), F.try_divide("drawn", "all_drawn").alias("drawn_share"))  # one row a stratum


def plan_mixture(counted: DataFrame, strata: list[str], work: Workspace, *, targets: Mapping[str, DataFrame] | None = None, exponent: float = 0.7, budget_share: float = 0.5, tolerance: float = 1e-13) -> Mixture:
    """The mixture for rows (strata, n_tokens)."""
    cells = work.keep(counted.groupBy(*strata).agg(F.sum("n_tokens").alias("tokens")), "cells")
    total = cells.agg(F.coalesce(F.sum("tokens"), F.lit(0))).first()[0]
    raked = rake(cells, strata, targets or {s: tempered(cells, s, exponent) for s in strata}, work, tolerance=tolerance)
    drawn = work.keep(calibrated(raked.cells, budget_share * float(total)), "drawn")
    work.forget("cells", "raked")
    return Mixture(tuple(strata), drawn, raked.passes, raked.gap)


def mix(df: DataFrame, strata: Mapping[str, Column], *, id_col: str = "doc_id", text_col: str = "text", tokens: Column | None = None, **settings) -> DataFrame:
    """The frame with stratum columns, n_tokens, probability and sampled.

    Null strata form the value ``(none)``.  Without targets, the shares of a stratum
    follow its tokens to the power ``exponent``.  The budget is ``budget_share`` of all
    tokens.  A cell without tokens has probability 0; columns of the output names are
    replaced, all others kept whatever their names; repeated rows are drawn together,
    null ids by their text; an empty table stays empty.
    """
    names = list(strata)
    own = fresh(df, *[f"stratum_{n}" for n in names], "counted_tokens", "probability_of_cell")
    keys, n, p = own[: len(names)], own[-2], own[-1]
    counted = df.withColumns(dict(zip(keys, (F.coalesce(c.cast("string"), F.lit(NONE)) for c in strata.values()), strict=True)) | {n: token_count(text_col) if tokens is None else tokens})
    slim = counted.select(*[F.col(k).alias(name) for k, name in zip(keys, names, strict=True)], F.col(n).alias("n_tokens"))
    drawn = plan_mixture(slim, names, Workspace(df.sparkSession, "mixing"), **settings).cells
    looked_up = _small(drawn.select(*[F.col(name).alias(k) for k, name in zip(keys, names, strict=True)], F.col("probability").alias(p)), drawn.count())
    joined = counted.join(looked_up, keys, "left").withColumn(p, F.coalesce(p, F.lit(0.0)))
    added = {*names, "n_tokens", "probability", "sampled"}
    carried = [F.col(f"`{c}`") for c in df.columns if c.lower() not in {a.lower() for a in added}]
    return joined.select(*carried, *[F.col(k).alias(name) for k, name in zip(keys, names, strict=True)], F.col(n).alias("n_tokens"), F.col(p).alias("probability"), (uniform(id_col, text_col) < F.col(p)).alias("sampled"))


def mix_documents(docs: DataFrame, **settings) -> DataFrame:
    """mix by source, language and surface topic."""
    return mix(docs, {"source": F.col("source"), "lang": F.col("lang"), "topic": surface_topic()}, **settings)


def oracle_sql(iterations: int = 40, exponent: float = 0.7, budget_share: float = 0.5, rounds: int = 24) -> str:
    """DuckDB SQL for mix_documents over documents, with passes and rounds enough to converge there."""
    count = lambda m: f"(length(t) - length(replace(t, '{m}', '')))"
    parts = [
        "WITH d AS (SELECT doc_id, coalesce(text, '') AS t, coalesce(source, '(none)') AS source, coalesce(lang, '(none)') AS lang FROM documents)",
        rf"""w AS (SELECT doc_id, source, lang, len(regexp_extract_all(t, '[^\x20\x09-\x0D]+'))::BIGINT AS n_tokens,
    CASE WHEN t = '' THEN 'empty' WHEN 40 * {count('|')} > length(t) THEN 'table'
         WHEN 40 * ({' + '.join(count(m) for m in '#*$%&')}) > length(t) THEN 'markup'
         WHEN 40 * {count('!')} > length(t) THEN 'exclaiming' WHEN length(t) < 400 THEN 'note'
         WHEN length(t) < 4000 THEN 'article' ELSE 'long read' END AS topic FROM d)""",
        "c AS (SELECT source, lang, topic, sum(n_tokens)::DOUBLE AS tokens FROM w GROUP BY ALL HAVING sum(n_tokens) > 0)",
        "r0 AS MATERIALIZED (SELECT *, tokens AS weight FROM c)",
    ]
    for s in ("source", "lang", "topic"):
        parts.append(f"s_{s} AS MATERIALIZED (SELECT {s}, pow(sum(tokens), {exponent}) / sum(pow(sum(tokens), {exponent})) OVER () AS share FROM c GROUP BY {s})")
    k = 0
    for _ in range(iterations):
        for s in ("source", "lang", "topic"):
            parts.append(f"r{k + 1} AS MATERIALIZED (SELECT source, lang, topic, tokens, weight * share / sum(weight) OVER (PARTITION BY {s}) AS weight FROM r{k} JOIN s_{s} USING ({s}))")
            k += 1
    parts.append("f0 AS MATERIALIZED (SELECT 0.0::DOUBLE AS f)")
    for i in range(rounds):
        parts.append(
            f"f{i + 1} AS MATERIALIZED (SELECT greatest(0.0, {budget_share} * (SELECT sum(tokens) FROM c) - coalesce(sum(tokens) FILTER (weight * f >= tokens), 0))"
            f" / sum(weight) FILTER (weight * f < tokens) AS f FROM r{k}, f{i})"
        )
    parts.append(f"p AS (SELECT source, lang, topic, least(1.0, weight * f / tokens) AS probability FROM r{k}, f{rounds})")
    return (
        ",\n".join(parts)
        + "\nSELECT doc_id, source, lang, topic, n_tokens, round(coalesce(probability, 0.0), 9) AS probability,"
        + " (('0x' || substr(md5(doc_id::VARCHAR), 1, 13))::BIGINT / 4503599627370496.0) < coalesce(probability, 0.0) AS sampled\nFROM w LEFT JOIN p USING (source, lang, topic)"
    )
