"""Mixing sources to target weights by iterative proportional fitting, in DataFrame functions only.

Token counts are summed to cells of source, language and topic, with a partial sum in every task. The cell weights are
raked under a cap: scaled to the source marginal, then the language marginal, then the topic marginal, round after round,
and no cell above the tokens that it has. A cell's documents are then kept with one probability, the tokens that its weight
asks for over those that it has, so the expected sample meets every target that can be met; the largest gap is reported.
A document's draw is a hash of its id and never changes.
"""

from __future__ import annotations

import logging

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from privgrove.llm.textio import free_names, stored

SIDES = ("source", "lang", "topic")
WORDS = r"[^ \t\n\r]+"
#: Exponent of each marginal's shares: 1 keeps them, 0 makes them equal.
SMOOTHING = {"source": 0.7, "lang": 0.8, "topic": 0.9}
#: Share of the tokens to keep, rounds at most, and the gap at which raking ends sooner.
KEEP, ROUNDS, CLOSE = 0.7, 12, 1e-13
#: Cells that one task rakes; more of them are dealt out by side, with the same results.
FEW_CELLS = 100_000
#: Topics of running text: classes of the initials of its words of seven letters or more.
LONG_WORD, CLASSES = r"([a-z])[a-z]{6,}", 8
LETTERS = "abcdefghijklmnopqrstuvwxyz"
DIGITS = "".join(str(k % CLASSES) for k in range(len(LETTERS)))

log = logging.getLogger(__name__)


def topic_of(text: Column) -> Column:
    """A text's topic: legal notices, tables and contact data by their form; running text by its vocabulary, the class
    that most of its long words' initials fall in, the first of equal ones; texts without long words are `other`."""
    low = F.lower(text)
    legal = low.contains("licen") | low.contains("rights reserved")
    initials = F.translate(F.array_join(F.regexp_extract_all(low, F.lit(LONG_WORD), F.lit(1)), ""), LETTERS, DIGITS)
    # a transform of one element names a value, so that it is not worked out again where it is used
    counted = F.transform(F.array(initials), lambda i: F.array(*[F.length(i) - F.length(F.replace(i, F.lit(str(k)), F.lit(""))) for k in range(CLASSES)]))
    named = F.transform(counted, lambda c: F.when(F.array_max(c) == 0, "other").otherwise(F.concat(F.lit("words-"), (F.array_position(c, F.array_max(c)) - 1).cast("string"))))
    return F.when(legal, "legal").when(text.contains(" | "), "table").when(text.contains("@"), "contact").otherwise(F.element_at(named, 1))


def draw_of(key: Column) -> Column:
    """A fixed uniform number in (0, 1) for each id."""
    digits = F.substring(F.sha2(F.concat(F.lit("mix|"), F.coalesce(key.cast("string"), F.lit(""))), 256), 1, 13)
    return (F.conv(digits, 16, 10).cast("long") + 0.5) / F.lit(float(1 << 52))


def with_targets(cells: DataFrame, smoothing: dict[str, float], keep: float) -> DataFrame:
    """Cells (source, lang, topic, tokens) with the smoothed marginal shares as targets, weight and cap.

    A weight is a share of the sample's tokens; the cap is all tokens of the cell, as such a share.
    """
    everything = Window.partitionBy()
    for side in SIDES:
        share = F.pow(F.sum("tokens").over(Window.partitionBy(side)) / F.sum("tokens").over(everything), smoothing[side])
        cells = cells.withColumn(f"_{side}", share).withColumn("_one", F.row_number().over(Window.partitionBy(side).orderBy(*SIDES)) == 1)
        cells = cells.withColumn(f"_{side}", F.col(f"_{side}") / F.sum(F.when(F.col("_one"), F.col(f"_{side}"))).over(everything)).drop("_one")
    return cells.withColumn("weight", F.col("tokens") / F.sum("tokens").over(everything)).withColumn("cap", F.col("weight") / F.lit(keep))


def raked(cells: DataFrame, rounds: int, few: bool = False) -> DataFrame:
    """Cells with their raked weight; `few` cells stay in one partition, where no step needs an exchange.

    A side whose value has too much is scaled down whole; one that has too little is made up by its cells below their cap.
    """
    for k in range(rounds):
        for side in SIDES:
            over = Window.partitionBy(side)
            full = F.col("weight") >= F.col("cap")
            own, capped = F.sum("weight").over(over), F.sum(F.when(full, F.col("weight")).otherwise(0.0)).over(over)
            more = F.when(full, F.col("cap")).otherwise(F.least(F.col("cap"), F.col("weight") * (F.col(f"_{side}") - capped) / (own - capped)))
            cells = cells.withColumn("weight", F.when(own >= F.col(f"_{side}"), F.col("weight") * F.col(f"_{side}") / own).otherwise(more))
        if k % 2 or k == rounds - 1:
            cells = stored(cells, "raked")
            cells = cells.coalesce(1) if few else cells
            if (gaps(cells).agg(F.max("gap")).first()[0] or 0.0) < CLOSE:
                break
    return cells


def gaps(cells: DataFrame) -> DataFrame:
    """How far raked cells are from each target: side, value, target, expected, gap, all as shares of the sample asked for."""
    sides = [cells.groupBy(F.lit(s).alias("side"), F.col(s).alias("value")).agg(F.first(f"_{s}").alias("target"), F.sum("weight").alias("expected")) for s in SIDES]
    return sides[0].unionByName(sides[1]).unionByName(sides[2]).withColumn("gap", F.abs(F.col("target") - F.col("expected")))


def planned(cells: DataFrame, keep: float = KEEP, smoothing: dict[str, float] | None = None, rounds: int = ROUNDS) -> tuple[DataFrame, DataFrame]:
    """(cells with weight and probability, gaps) of cells (source, lang, topic, tokens); cells of no tokens have no part."""
    cells = cells.where("tokens > 0")
    few = cells.count() <= FEW_CELLS
    cells = with_targets(cells.coalesce(1) if few else cells, {**SMOOTHING, **(smoothing or {})}, keep)
    cells = raked(stored(cells, "targets").coalesce(1) if few else stored(cells, "targets"), rounds, few)
    chance = F.round(F.least(F.lit(1.0), F.col("weight") / F.col("cap")), 9)
    return cells.select(*SIDES, "tokens", "weight", chance.alias("probability")), gaps(cells)


def sampled(docs: DataFrame, keep: float = KEEP, smoothing: dict[str, float] | None = None, rounds: int = ROUNDS, topic: Column | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents drawn, with their own columns and one more, `mix`: a struct of source, lang, topic, tokens and
    probability. Where docs has columns of that name, the struct is the last column under the name with lines before it.

    Null sides form a value of their own, `none`; a null id draws as the empty string. Documents without tokens (null,
    empty or white texts) carry no weight and are kept. Rows that repeat an id share its draw. An empty table gives no
    rows. Targets that the cells can't meet are logged as a warning with the largest gap.
    """
    mix, cell, chance = free_names(docs.columns, "mix", "cell", "chance")
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    side = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("none"))
    own = F.struct(side("source").alias("source"), side("lang").alias("lang"), (topic if topic is not None else topic_of(text)).alias("topic"))
    rows = docs.withColumns({cell: own, mix: F.regexp_count(text, F.lit(WORDS)).cast("long")})
    cells = stored(rows.groupBy(F.col(cell).alias("cell")).agg(F.sum(mix).alias("tokens")).select("cell.*", F.col("tokens").cast("double").alias("tokens")), "cells")
    plan, missed = planned(cells, keep, smoothing, rounds)
    plan = stored(plan, "probabilities")
    worst = missed.orderBy(F.desc("gap"), "side", "value").first()
    if worst and worst["gap"] > 1e-6:
        log.warning("the mix misses targets, most for %s %s: %.6f in place of %.6f", worst["side"], worst["value"], worst["expected"], worst["target"])
    joined = rows.join(plan.select(F.struct(*SIDES).alias(cell), F.col("probability").alias(chance)), cell, "left")
    joined = joined.withColumn(chance, F.when(F.col(mix) == 0, F.lit(1.0)).otherwise(F.col(chance)))
    shown = F.struct(*[F.col(cell)[s].alias(s) for s in SIDES], F.col(mix).alias("tokens"), F.col(chance).alias("probability"))
    return joined.where(draw_of(F.col(id_col)) < F.col(chance)).select(*[F.col(f"`{c}`") for c in docs.columns], shown.alias(mix))


def sample_sql(table: str = "documents", keep: float = KEEP, rounds: int = ROUNDS) -> str:
    """The same sample as DuckDB SQL."""
    steps = []
    for _ in range(rounds):
        for side in SIDES:
            source = f"w{len(steps)}"
            steps.append(
                f"w{len(steps) + 1} AS MATERIALIZED (SELECT * EXCLUDE (weight, own, capped), CASE WHEN own >= t_{side} THEN weight * t_{side} / own WHEN weight >= cap THEN cap ELSE least(cap, weight * (t_{side} - capped) / (own - capped)) END AS weight"
                f" FROM (SELECT *, sum(weight) OVER (PARTITION BY {side}) AS own, sum(CASE WHEN weight >= cap THEN weight ELSE 0.0 END) OVER (PARTITION BY {side}) AS capped FROM {source}))"
            )
    shares = ", ".join(f"{s}s AS (SELECT {s}, pow(sum(tokens) / (SELECT sum(tokens) FROM cells), {SMOOTHING[s]}) AS share FROM cells GROUP BY {s})" for s in SIDES)
    targets = ", ".join(f"{s}s.share / (SELECT sum(share) FROM {s}s) AS t_{s}" for s in SIDES)
    counts = [f"(length(i) - length(replace(i, '{k}', '')))" for k in range(CLASSES)]
    most = f"greatest({', '.join(counts)})"
    words = " ".join(f"WHEN {c} = {most} THEN 'words-{k}'" for k, c in enumerate(counts))
    return f"""
    WITH docs AS (SELECT doc_id, coalesce(source, 'none') AS source, coalesce(lang, 'none') AS lang,
      CASE WHEN contains(lower(t), 'licen') OR contains(lower(t), 'rights reserved') THEN 'legal' WHEN contains(t, ' | ') THEN 'table' WHEN contains(t, '@') THEN 'contact' WHEN {most} = 0 THEN 'other' {words} END AS topic,
      CAST(len(regexp_extract_all(t, '{WORDS}')) AS BIGINT) AS n_tokens
      FROM (SELECT *, translate(array_to_string(regexp_extract_all(lower(t), '{LONG_WORD}', 1), ''), '{LETTERS}', '{DIGITS}') AS i FROM (SELECT *, coalesce(text, '') AS t FROM {table}))),
    cells AS MATERIALIZED (SELECT source, lang, topic, CAST(sum(n_tokens) AS DOUBLE) AS tokens FROM docs GROUP BY ALL HAVING sum(n_tokens) > 0),
    {shares},
    w0 AS MATERIALIZED (SELECT cells.*, {targets}, tokens / (SELECT sum(tokens) FROM cells) AS weight, tokens / (SELECT sum(tokens) FROM cells) / {keep} AS cap FROM cells {" ".join(f"JOIN {s}s USING ({s})" for s in SIDES)}),
    {", ".join(steps)},
    p AS (SELECT source, lang, topic, round(least(1.0, weight / cap), 9) AS probability FROM w{len(steps)}),
    j AS (SELECT doc_id, source, lang, topic, n_tokens, CASE WHEN n_tokens = 0 THEN 1.0 ELSE probability END AS probability FROM docs LEFT JOIN p USING (source, lang, topic))
    SELECT * FROM j WHERE (CAST('0x' || substr(sha256('mix|' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 13) AS BIGINT) + 0.5) / 4503599627370496.0 < probability
    """
