"""Mixing sources to target weights by Poisson replication, in DataFrame functions only.

A source's rate is its target share of the corpus over its present share. Each
document's number of copies is a Poisson number with that rate, found by
inverting the distribution at a uniform number that a hash of (seed, document)
gives; so it does not depend on partitions, retries or other documents. Copies
are exploded and shuffled globally by a hash of their own.

Defined cases: a null source is a source of its own; a null text counts as
empty; a size is bytes plus one, so that empty texts count too; a document
without an id is drawn by its text; rows that repeat an id get the same number
of copies each; an empty table gives an empty result; rates of any size are
exact, large ones are drawn as sums of smaller ones.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spreadmax.llm.common import columns, fresh

SEED = 20
#: Without given weights a source's target share is its size to this power.
FLATTEN = 0.5
#: A rate beyond it is drawn in equal parts.
PART = 16.0
#: Steps of the distribution that are tabulated; beyond it the tail of a part is below 2**-53.
STEPS = 80
#: Sources up to this number are broadcast, more are joined by a shuffle.
BROADCAST_ROWS = 100_000


def uniform(*keys: Column) -> Column:
    """A uniform number in [0, 1) of 48 bits, from md5 of the keys."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *keys)), 1, 12), 16, 10).cast("double") / float(1 << 48)


def source_rates(docs: DataFrame, weights: dict[str, float] | None = None, flatten: float = FLATTEN) -> DataFrame:
    """(source, rate): the mean number of copies of each document of a source."""
    size = F.octet_length(F.coalesce(F.col("text"), F.lit(""))).cast("long") + 1
    sizes = docs.groupBy("source").agg(F.sum(size).alias("size"))
    if weights is None:
        target = F.pow(F.col("size").cast("double"), F.lit(flatten))
    else:
        target = F.lit(0.0)
        for name, w in sorted(weights.items()):
            target = F.when(F.col("source") == name, float(w)).otherwise(target)
    weighed = sizes.select("source", "size", target.alias("target"))
    total = weighed.agg(F.sum("size").alias("all"), F.sum("target").alias("targets")).head()
    everything, targets = float(total["all"] or 0), float(total["targets"] or 0) or 1.0
    return weighed.select("source", (F.col("target") / targets * everything / F.col("size")).alias("rate"))


def _table(rate: Column) -> Column:
    """The distribution function of Poisson(rate) at 0, 1, 2, ..."""
    begin = F.exp(-rate)
    steps = F.aggregate(
        F.sequence(F.lit(1), F.lit(STEPS)),
        F.struct(begin.alias("p"), F.array(begin).alias("sums")),
        lambda acc, k: F.struct(
            (acc["p"] * rate / k).alias("p"),
            F.concat(acc["sums"], F.array(F.element_at(acc["sums"], -1) + acc["p"] * rate / k)).alias("sums"),
        ),
    )
    return steps["sums"]


RESULT = ("rate", "copies", "copy", "mix_key")


def replicate(
    docs: DataFrame, weights: dict[str, float] | None = None, flatten: float = FLATTEN, seed: int = SEED
) -> DataFrame:
    """`docs` with rate, copies (of the document), copy (from 1) and mix_key, one row per copy, not yet shuffled.

    A result column whose name is taken gets an underscore; columns of `docs` stay as they are.
    """
    rate, copies, copy, mix_key = fresh(docs.columns, *RESULT)
    of, parts, table, name, drawn = fresh([*docs.columns, rate, copies, copy, mix_key], "of_source", "parts", "distribution", "name", "drawn")
    rates = source_rates(docs, weights, flatten)
    rates = rates.select(
        F.col("source").alias(of), F.col("rate").alias(rate), F.greatest(F.lit(1), F.ceil(F.col("rate") / PART)).cast("int").alias(parts)
    ).withColumn(table, _table(F.col(rate) / F.col(parts)))
    if rates.count() <= BROADCAST_ROWS:
        rates = F.broadcast(rates)
    own = F.coalesce(F.col("doc_id").cast("string"), F.md5(F.coalesce(F.col("text"), F.lit(""))))
    joined = docs.join(rates, F.col("source").eqNullSafe(F.col(of))).drop(of).withColumn(name, own)
    draws = F.transform(
        F.sequence(F.lit(1), F.col(parts)),
        lambda j: uniform(F.lit(str(seed)), j.cast("string"), F.col(name)),
    )
    count = F.aggregate(
        F.col(drawn), F.lit(0), lambda acc, u: acc + F.size(F.filter(table, lambda c: c <= u))
    )
    counted = joined.withColumn(drawn, draws).withColumn(copies, count).drop(drawn, table, parts)
    each = counted.filter(F.col(copies) > 0).withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(copies))))
    key = F.md5(F.concat_ws(":", F.lit(f"order{seed}"), F.col(copy).cast("string"), F.col(name)))
    return each.withColumn(mix_key, F.substring(key, 1, 16)).drop(name)


def mix(docs: DataFrame, weights: dict[str, float] | None = None, flatten: float = FLATTEN, seed: int = SEED) -> DataFrame:
    """The mixture in a global random order, with the columns of `docs`; copies are repeated rows."""
    out = replicate(docs, weights, flatten, seed)
    key = fresh(docs.columns, *RESULT)[-1]
    return out.repartition(key).sortWithinPartitions(key).select(*columns(docs))
