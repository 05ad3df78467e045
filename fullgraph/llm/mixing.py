"""Mixing sources to target weights by iterative proportional fitting (raking).

Tokens are summed per cell (source x language x topic).  Raking scales the cells
until the totals of each margin meet its target shares; a cell's factor is the
weight of its documents' tokens.  Documents are then sampled with probability
``rate * factor``, where ``rate`` is the largest that keeps every probability at
most 1 (or what a token budget asks, if smaller), so the expected token shares
are the targets.  The draw of a document depends on its identifier and the seed
only.

Targets default to tempered shares (share ** ``TEMPER``, normalised).  The topic
of a document is given by ordered patterns (:data:`TOPICS`) where the table has
no ``topic`` column.  With default targets a factor is at most ``MAX_RATIO`` times
the token-weighted mean after every round, so that one rare cell does not thin out
all others; given targets are not trimmed unless ``max_ratio`` says so.  Targets
that no weights can meet (trimmed, or without tokens) are missed: :func:`margins`
reports every target beside what is achieved, and a miss above ``MISS`` is a warning.

Cells are rows of a margin table, counted with map-side partial sums.  Up to
``MAX_DRIVER_CELLS`` of them are raked in memory on the driver (the bound is
checked); beyond it the same rounds, up to the same tolerance, run as DataFrame
aggregates.

Defined results: null source, language or topic is a value of its own; null or
empty text has no tokens and is kept with its cell's probability; a table
without tokens keeps every row; repeated rows share one draw; a null ``doc_id``
has a draw of its own value; extra columns pass unread; an empty table gives an
empty result.
"""

from __future__ import annotations

import warnings

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import WS, fresh, spread, stored, text_of, unit_hash

MARGINS = ("source", "lang", "topic")
TEMPER = 0.9
MAX_RATIO = 2.0
MAX_DRIVER_CELLS = 200_000
ROUNDS = 50
TOLERANCE = 1e-10
MISS = 0.01
NONE = "(none)"

# Topics in order of precedence and the pattern that shows them.
TOPICS = (
    ("legal", "(?i)licen[sc]e|copyright|all rights reserved"),
    ("contact", "[A-Za-z0-9._-]+@[A-Za-z0-9-]+[.][a-z]"),
    ("markup", "[|#$%&<>]"),
    ("numeric", "[0-9]"),
)


def topic_of(text: Column) -> Column:
    out = F.lit("prose")
    for name, pattern in reversed(TOPICS):
        out = F.when(text.rlike(pattern), F.lit(name)).otherwise(out)
    return out


def described(docs: DataFrame) -> DataFrame:
    """doc_id, row_hash, the margins' values, n_tokens (words)."""
    docs = spread(docs.select("doc_id", "text", "source", "lang", *[c for c in docs.columns if c == "topic"]))
    text = text_of(docs)
    margin = lambda c: F.coalesce(docs[c].cast("string"), F.lit(NONE)).alias(c)
    topic = F.coalesce(docs["topic"].cast("string"), F.lit(NONE)) if "topic" in docs.columns else topic_of(text)
    squeezed = F.btrim(F.translate(text, WS, " " * len(WS)))
    n = F.when(squeezed == "", 0).otherwise(F.size(F.split(squeezed, " +", -1)))
    return docs.select(docs["doc_id"].alias("doc_id"), F.xxhash64(text).alias("row_hash"), margin("source"), margin("lang"), topic.alias("topic"), n.cast("long").alias("n_tokens"))


def tempered(totals: dict[str, float], power: float) -> dict[str, float]:
    part = {k: v**power if v > 0 else 0.0 for k, v in totals.items()}
    s = sum(part.values()) or 1.0
    return {k: v / s for k, v in part.items()}


def rake(tokens: np.ndarray, codes: list[np.ndarray], targets: list[np.ndarray], rounds: int = ROUNDS, max_ratio: float | None = MAX_RATIO) -> np.ndarray:
    """Factors per cell such that the weighted margins meet the target shares."""
    total = tokens.sum()
    factor = np.ones(len(tokens))
    if total <= 0:
        return factor
    for _ in range(rounds):
        worst = 0.0
        for code, target in zip(codes, targets):
            have = np.bincount(code, weights=tokens * factor, minlength=len(target)) / total
            step = np.divide(target, have, out=np.ones_like(target), where=have > 0)
            worst = max(worst, np.abs(np.where(have > 0, have - target, 0)).max())
            factor *= step[code]
        if max_ratio is not None:
            factor = np.minimum(factor, max_ratio * (tokens * factor).sum() / total)
        if worst < TOLERANCE:
            break
    return factor


def goals(spark: SparkSession, cells: DataFrame, targets: dict[str, dict[str, float]] | None, power: float) -> dict[str, DataFrame]:
    """Per margin (value, goal): given or tempered shares of the values that the cells have, normalised."""
    out = {}
    for m in MARGINS:
        have = cells.groupBy(F.col(m).alias("value")).agg(F.sum("tokens").cast("double").alias("t"))
        if targets and m in targets:
            given = spark.createDataFrame([(str(k), float(v)) for k, v in targets[m].items()], "value string, part double")
            part = have.join(given, "value", "left").select("value", F.coalesce("part", F.lit(0.0)).alias("part"))
        else:
            part = have.select("value", F.when(F.col("t") > 0, F.pow("t", F.lit(power))).otherwise(0.0).alias("part"))
        part = stored(spark, part, f"goal-{m}")
        s = float(part.agg(F.sum("part")).first()[0] or 0) or 1.0
        out[m] = part.select("value", (F.col("part") / F.lit(s)).alias("goal"))
    return out


def _driver_factors(spark: SparkSession, cells: DataFrame, goal: dict[str, DataFrame], max_ratio: float | None) -> DataFrame:
    rows = cells.collect()  # at most MAX_DRIVER_CELLS
    rows.sort(key=lambda r: tuple(r[m] for m in MARGINS))
    tokens = np.array([r.tokens for r in rows], dtype=float)
    codes, wanted = [], []
    for m in MARGINS:
        share = {r.value: r.goal for r in goal[m].collect()}  # at most as many values as cells
        names = sorted(share)
        place = {x: i for i, x in enumerate(names)}
        codes.append(np.array([place[r[m]] for r in rows], dtype=np.int64))
        wanted.append(np.array([share[x] for x in names]))
    factor = rake(tokens, codes, wanted, max_ratio=max_ratio)
    schema = ", ".join(f"{m} string" for m in MARGINS) + ", tokens long, factor double"
    return spark.createDataFrame([(*(r[m] for m in MARGINS), r.tokens, float(f)) for r, f in zip(rows, factor)], schema)


def _spark_factors(spark: SparkSession, cells: DataFrame, goal: dict[str, DataFrame], max_ratio: float | None, rounds: int = ROUNDS) -> DataFrame:
    total = float(cells.agg(F.sum("tokens")).first()[0] or 0)
    now = stored(spark, cells.withColumn("factor", F.lit(1.0)), "cells")
    for _ in range(rounds if total else 0):
        worst = 0.0
        for m in MARGINS:
            have = now.groupBy(F.col(m).alias("value")).agg((F.sum(F.col("tokens") * F.col("factor")) / total).alias("have"))
            step = stored(spark, have.join(goal[m], "value"), f"step-{m}")
            worst = max(worst, step.agg(F.max(F.when(F.col("have") > 0, F.abs(F.col("have") - F.col("goal"))))).first()[0] or 0.0)
            ratio = F.when(F.col("have") > 0, F.col("goal") / F.col("have")).otherwise(1.0)
            now = now.join(step.select(F.col("value").alias(m), ratio.alias("step")), m).select(*MARGINS, "tokens", (F.col("factor") * F.col("step")).alias("factor"))
        if max_ratio is not None:
            mean = float(now.agg(F.sum(F.col("tokens") * F.col("factor"))).first()[0]) / total
            now = now.withColumn("factor", F.least("factor", F.lit(max_ratio * mean)))
        now = stored(spark, now, "cells")
        if worst < TOLERANCE:
            break
    return now


def margins(cells: DataFrame, goal: dict[str, DataFrame]) -> DataFrame:
    """margin, value, target, achieved: the share of the expected tokens beside the target."""
    mass = F.col("tokens") * F.col("factor")
    total = cells.agg(F.sum(mass).alias("total"))
    out = None
    for m in MARGINS:
        have = cells.groupBy(F.col(m).alias("value")).agg(F.sum(mass).alias("mass"))
        one = have.join(goal[m], "value").crossJoin(F.broadcast(total)).select(F.lit(m).alias("margin"), "value", F.col("goal").alias("target"), F.when(F.col("total") > 0, F.col("mass") / F.col("total")).otherwise(0.0).alias("achieved"))
        out = one if out is None else out.unionByName(one)
    return out


def cell_factors(spark: SparkSession, facts: DataFrame, targets: dict[str, dict[str, float]] | None = None, power: float = TEMPER, max_driver_cells: int = MAX_DRIVER_CELLS, max_ratio: float | None = None) -> tuple[DataFrame, DataFrame]:
    """(source, lang, topic, tokens, factor of every cell; :func:`margins` of them)."""
    cells = stored(spark, facts.groupBy(*MARGINS).agg(F.sum("n_tokens").alias("tokens")), "cells")
    if max_ratio is None and not targets:
        max_ratio = MAX_RATIO
    goal = goals(spark, cells, targets, power)
    way = _driver_factors if cells.count() <= max_driver_cells else _spark_factors
    out = way(spark, cells, goal, max_ratio)
    reached = margins(out, goal)
    miss = reached.agg(F.max(F.when(F.col("achieved") > 0, F.abs(F.col("target") - F.col("achieved"))).otherwise(F.col("target")))).first()[0]
    if miss is not None and miss > MISS and any(r.tokens for r in out.select("tokens").filter("tokens > 0").limit(1).collect()):
        warnings.warn(f"a margin misses its target share by {miss:.3f}; see margins()", stacklevel=3)
    return out, reached


def chances(spark: SparkSession, docs: DataFrame, targets: dict[str, dict[str, float]] | None = None, budget: float | None = None, seed: int = 4, power: float = TEMPER, max_driver_cells: int = MAX_DRIVER_CELLS, max_ratio: float | None = None) -> DataFrame:
    """doc_id, row_hash, source, lang, topic, n_tokens, weight, probability, selected of every row.

    The texts are read once; their facts are a narrow table that both the raking and the draw use.
    """
    facts = stored(spark, described(docs), "facts")
    cells, _ = cell_factors(spark, facts, targets, power, max_driver_cells, max_ratio)
    r = cells.agg(F.max(F.when(F.col("tokens") > 0, F.col("factor"))).alias("top"), F.sum(F.col("tokens") * F.col("factor")).alias("mass")).first()
    rate = 1.0 / r.top if r.top else 1.0
    if budget is not None and r.mass:
        rate = min(rate, budget / r.mass)
    weights = cells.select(*MARGINS, F.col("factor").alias("weight"), F.least(F.lit(1.0), F.col("factor") * rate).alias("probability"))
    return facts.join(weights, list(MARGINS), "left").select("doc_id", "row_hash", *MARGINS, "n_tokens", "weight", "probability", (unit_hash(F.col("doc_id"), seed) < F.col("probability")).alias("selected"))


def calibrated(spark: SparkSession, docs: DataFrame, **options) -> DataFrame:
    """doc_id, source, lang, topic, n_tokens, weight, probability, selected of every row."""
    return chances(spark, docs, **options).drop("row_hash")


def achieved(spark: SparkSession, docs: DataFrame, targets: dict[str, dict[str, float]] | None = None, power: float = TEMPER, **options) -> DataFrame:
    """margin, value, target, achieved of the weights that :func:`calibrated` uses."""
    return cell_factors(spark, stored(spark, described(docs), "facts"), targets, power, **options)[1]


def mix(spark: SparkSession, docs: DataFrame, **options) -> DataFrame:
    """The sampled rows of ``docs``, all columns."""
    key, digest = fresh(docs, "_id"), fresh(docs, "_hash")
    drawn = chances(spark, docs, **options).filter("selected").select(F.col("doc_id").alias(key), F.col("row_hash").alias(digest)).distinct()
    return docs.join(drawn.hint("shuffle_hash"), docs["doc_id"].eqNullSafe(F.col(key)) & (F.xxhash64(text_of(docs)) == F.col(digest)), "left_semi")
