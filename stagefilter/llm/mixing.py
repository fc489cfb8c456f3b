"""Operator 4: mixing sources to target weights by capped water-filling, in DataFrame functions only.

Sources share a total by weight; a source whose share passes its cap (a maximum number of
epochs times its size) is clamped there and the excess goes to the others by weight, until
no share is above its cap. The fixed point is found in closed form: with sources in the
order of cap over weight, the clamped ones are a head of that order, so running sums give
the level at which the rest fills up.

Documents are then taken in whole repetitions: everything floor(target / size) times, and
once more the documents whose seeded hash bucket lies before the bucket where the
remaining words end; documents inside that one bucket are taken in a fraction, rounded
by their own seeded hash. Reruns agree since only hashes of the document decide.

Edge cases: null text has size 0; a null source is a source of its own, last in order;
a source of size 0 has target 0; repeated rows count as separate documents and share a
hash; no sources give an empty result; extra columns are kept out of the way.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stagefilter.llm.common import OTHER_SPACE, cut, let, words


@dataclass(frozen=True)
class Mix:
    """weights: repeat over the sources in code point order, null last; total: words to take as a share of all; epochs: most repetitions of a source; buckets: hash buckets a source's documents fall in; broadcast_sources: most sources whose plan, a row each, is broadcast; more are joined by shuffling."""

    weights: tuple[float, ...] = (5, 2, 1)
    total: float = 1.5
    epochs: float = 2.0
    buckets: int = 1024
    seed: int = 20240
    broadcast_sources: int = 200_000


def size_of(text: Column) -> Column:
    return F.size(words(text)).cast("long")


def water_fill(sources: DataFrame, cfg: Mix) -> DataFrame:
    """sources (source, source_size; one row each) with weight and target added.

    The two windows run over one row per source, that is over an aggregate.
    """
    place = Window.orderBy(F.col("source").isNull(), F.col("source"))
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in cfg.weights]), (F.row_number().over(place) - 1) % len(cfg.weights) + 1)
    head = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").isNull(), F.col("source"))
    before = head.rowsBetween(Window.unboundedPreceding, -1)
    after = head.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    everything = head.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    caps = sources.select("source", "source_size", weight.alias("weight")).withColumn("cap", F.col("source_size") * F.lit(float(cfg.epochs)))
    level = (F.sum("source_size").over(everything) * F.lit(float(cfg.total)) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(after)
    levels = caps.withColumn("level", level)
    # the first source in this order whose cap is above the level names the level of all later ones
    free = F.min(F.when(F.col("cap") > F.col("level") * F.col("weight"), F.struct((F.col("cap") / F.col("weight")).alias("o"), F.col("level").alias("level")))).over(everything)
    return levels.withColumn("free", free.getField("level")).select(
        "source", "source_size", "weight", F.when(F.col("free").isNull(), F.col("cap")).otherwise(F.least(F.col("cap"), F.col("free") * F.col("weight"))).alias("target")
    )


def _bucket(cfg: Mix) -> Column:
    return F.pmod(F.xxhash64(F.lit(cfg.seed), F.col("doc_id")), F.lit(cfg.buckets)).cast("int")


def mix_plan(docs: DataFrame, cfg: Mix = Mix()) -> DataFrame:
    """Columns doc_id, text, source and what else docs has, with size, source_size, target, whole and taken."""
    sized = docs.withColumn("size", size_of(F.col("text"))).withColumn("bucket", _bucket(cfg))
    cells = sized.groupBy("source", "bucket").agg(F.sum("size").alias("cell"))
    sources = water_fill(cells.groupBy("source").agg(F.sum("cell").alias("source_size")), cfg)
    key = lambda side: [F.col(f"{side}.source").eqNullSafe(F.col("p.source"))]
    in_order = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    plan = cells.alias("c").join(sources.alias("p"), key("c")[0]).select("p.source", "bucket", "cell", "source_size", "target")
    whole = F.coalesce(F.floor(F.try_divide(F.col("target"), F.col("source_size"))), F.lit(0)).cast("long")
    rest = F.col("target") - F.col("whole") * F.col("source_size") - F.coalesce(F.sum("cell").over(in_order), F.lit(0))
    plan = plan.withColumn("whole", whole).withColumn("share", F.least(F.lit(1.0), F.greatest(F.lit(0.0), F.coalesce(F.try_divide(rest, F.col("cell")), F.lit(0.0)))))
    # in bucket order a source is taken whole, then one bucket in part, then nothing: one row per source says it all
    part = F.max(F.when((F.col("share") > 0) & (F.col("share") < 1), F.struct("bucket", "share")))
    plan = plan.groupBy(F.col("source").alias("p_source"), "source_size", "target", "whole").agg(F.max(F.when(F.col("share") >= 1, F.col("bucket"))).alias("full_to"), part.alias("part"))
    plan = cut(plan)
    if plan.count() <= cfg.broadcast_sources:
        joined = sized.join(F.broadcast(plan), F.col("source").eqNullSafe(F.col("p_source")))
    else:  # by source and bucket, so that a hot source is spread
        spread = plan.withColumn("p_bucket", F.explode(F.sequence(F.lit(0), F.lit(cfg.buckets - 1))))
        joined = sized.join(spread, F.col("source").eqNullSafe(F.col("p_source")) & (F.col("bucket") == F.col("p_bucket"))).drop("p_bucket")
    share = F.when(F.col("bucket") <= F.col("full_to"), 1.0).when(F.col("bucket") == F.col("part.bucket"), F.col("part.share")).otherwise(0.0)
    dither = F.pmod(F.xxhash64(F.lit(cfg.seed + 1), F.col("doc_id")), F.lit(1 << 20)) / F.lit(float(1 << 20))
    extra = F.least(F.col("size"), F.floor(share * F.col("size") + dither)).cast("long")
    return joined.withColumn("taken", F.col("whole") * F.col("size") + extra).drop("p_source", "bucket", "full_to", "part")


def mix_sources(docs: DataFrame, cfg: Mix = Mix()) -> DataFrame:
    """One row per document: doc_id, size, source_size, target, taken."""
    return mix_plan(docs.select("doc_id", "text", "source"), cfg).select("doc_id", "size", "source_size", "target", "taken")


def mixed_documents(docs: DataFrame, cfg: Mix = Mix()) -> DataFrame:
    """The mixed corpus with the columns of docs: whole repetitions as repeated rows, a fractional one as the document's text up to the end of its last word taken, white space and all."""
    names = docs.columns
    plan = mix_plan(docs.select("doc_id", "text", "source", *[F.col(f"`{c}`").alias(f"_own_{i}") for i, c in enumerate(names)]), cfg)
    copies = F.when(F.col("size") > 0, F.floor(F.col("taken") / F.col("size"))).otherwise(F.col("whole"))
    part = F.when(F.col("size") > 0, F.col("taken") % F.col("size")).otherwise(F.lit(0))
    n = (copies + F.when(part > 0, 1).otherwise(0)).cast("int")
    rows = plan.withColumn("_part", part).withColumn("_copies", copies).filter(n > 0).withColumn("_copy", F.explode(F.sequence(F.lit(1), n)))
    spaced = F.translate("text", OTHER_SPACE, " " * len(OTHER_SPACE))
    # the pieces that are words; the text up to the last one taken stays as it is
    def taken(pieces: Column) -> Column:
        words_at = F.filter(F.sequence(F.lit(1), F.size(pieces)), lambda i: F.get(pieces, i - 1) != "")
        last = F.get(words_at, F.greatest(F.col("_part"), F.lit(1)).cast("int") - 1)
        return F.length(F.array_join(F.slice(pieces, F.lit(1), last), " "))

    # the pieces are bound once: inside a function over places they would be cut anew for each
    head = F.substring("text", F.lit(1), let(F.split(spaced, " "), taken))
    text = F.when(F.col("_copy") > F.col("_copies"), head).otherwise(F.col("text"))
    own = {"text": text, "n_chars": F.when(F.col("_copy") > F.col("_copies"), F.length(head)).otherwise(F.col(f"_own_{names.index('n_chars')}")) if "n_chars" in names else None}
    return rows.select(*[(own[c] if c in own else F.col(f"_own_{i}")).cast(docs.schema[c].dataType).alias(c) for i, c in enumerate(names)])
