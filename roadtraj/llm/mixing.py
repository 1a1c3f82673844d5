"""Mixing sources to target weights by pivotal dependent rounding.

Each source gets a target number of words; every document of the source then
has the same expected number of copies, target / source size. The whole part is
certain; the fraction is rounded by the pivotal method: two units meet, mass
moves at random from one to the other until one is 0 or 1, and the other goes
on. Units meet inside chunks of bounded size, ordered by their words so that
mass moves between documents of like size; what remains of a chunk is one unit,
and these meet in chunks of the next level: a reduction tree of log depth.
All of it is built-in DataFrame expressions; every draw is a hash of the seed
and the two units, so a rerun gives the same mix.

Defined results: a null text has size 0; a null source is a source of its own,
last in order; repeated rows are units of their own; an empty table gives an
empty table; columns beyond doc_id, text and source are ignored by ``mix``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from roadtraj.llm.scratch import materialize

WEIGHTS = (3, 1, 2)
SHARE = 1.5
MOST_COPIES = 2
CHUNK = 256
_UNIT = "struct<size: bigint, id: bigint, key: bigint, p: double>"


def word_count(text: Column) -> Column:
    trimmed = F.btrim(F.coalesce(text, F.lit("")), F.lit(" \t\n\x0b\x0c\r"))
    return F.when(trimmed == "", F.lit(0)).otherwise(F.size(F.split(trimmed, r"[\x20\x09-\x0D]+"))).cast("long")


def targets(sizes: DataFrame, weights=WEIGHTS, share=SHARE, most=MOST_COPIES) -> DataFrame:
    """source, n_units, source_size, target: shares by weight, none above ``most`` times its source.

    The level that makes the capped shares meet the total is found in one pass
    over the sources ordered by cap / weight.
    """
    by_name, by_ratio = Window.orderBy(F.col("source").asc_nulls_last()), Window.orderBy("_ratio", "source")
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), ((F.row_number().over(by_name) - 1) % len(weights) + 1).cast("int"))
    per = sizes.groupBy("source").agg(F.count(F.lit(1)).alias("n_units"), F.sum("size").alias("source_size"))
    ranked = per.withColumn("_w", weight).withColumn("_cap", F.col("source_size") * float(most)).withColumn("_ratio", F.col("_cap") / F.col("_w"))
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    after = by_ratio.rowsBetween(0, Window.unboundedFollowing)
    level = (F.sum("source_size").over(Window.partitionBy()) * float(share) - F.coalesce(F.sum("_cap").over(before), F.lit(0.0))) / F.sum("_w").over(after)
    leveled = ranked.withColumn("_level", level).withColumn("_fits", F.when(F.col("_level") <= F.col("_ratio") * (1 + 1e-12), F.col("_level")))
    water = F.first("_fits", ignorenulls=True).over(by_ratio.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return leveled.withColumn("target", F.least(F.col("_cap"), water * F.col("_w"))).select("source", "n_units", "source_size", "target")


def _meet(seed: int) -> Column:
    """Fold of one chunk's ordered units: the decided ones and the unit that remains."""
    draw = f"shiftrightunsigned(xxhash64({seed}L, a.rest.id, a.rest.key, x.id, x.key), 11) / 9007199254740992.0D"
    unit = "named_struct('size', {u}.size, 'id', {u}.id, 'key', {u}.key, 'p', {p})"
    won, lost = "named_struct('unit', {u}, 'take', 1)", "named_struct('unit', {u}, 'take', 0)"
    total = "(a.rest.p + x.p)"
    step = f"""
      CASE WHEN a.rest IS NULL THEN named_struct('rest', x, 'done', a.done)
      WHEN {total} < 1 AND {draw} * {total} < x.p
        THEN named_struct('rest', {unit.format(u='x', p=total)}, 'done', concat(a.done, array({lost.format(u='a.rest')})))
      WHEN {total} < 1
        THEN named_struct('rest', {unit.format(u='a.rest', p=total)}, 'done', concat(a.done, array({lost.format(u='x')})))
      WHEN {draw} * (2 - {total}) < 1 - x.p
        THEN named_struct('rest', {unit.format(u='x', p=f'{total} - 1')}, 'done', concat(a.done, array({won.format(u='a.rest')})))
      ELSE named_struct('rest', {unit.format(u='a.rest', p=f'{total} - 1')}, 'done', concat(a.done, array({won.format(u='x')}))) END"""
    return F.expr(f"aggregate(units, named_struct('rest', cast(null as {_UNIT}), 'done', cast(array() as array<struct<unit: {_UNIT}, take: int>>)), (a, x) -> {step})")


def round_copies(units: DataFrame, group: str, seed: int = 7, chunk: int = CHUNK) -> DataFrame:
    """Dependent rounding of ``p`` in each ``group``: rows (group, unit, take).

    ``units`` has ``group``, ``chunks`` (chunks of its group) and ``unit``, a
    struct of size, id, key and p in (0, 1). A chunk holds about ``chunk`` units.
    """
    level = units.select(group, F.pmod(F.xxhash64(F.lit(seed), "unit.id", "unit.key"), F.col("chunks")).alias("slot"), "unit")
    depth, left = 1, units.agg(F.max("chunks")).first()[0] or 1
    while left > 1:
        left = -(-left // chunk)
        depth += 1
    decided = None
    for n in range(depth):
        met = level.groupBy(group, "slot").agg(F.sort_array(F.collect_list("unit")).alias("units")).select(group, "slot", _meet(seed + n).alias("a"))
        met = materialize(met.select(group, "slot", "a.rest", "a.done"), f"round{n}")
        done = met.select(group, F.explode("done").alias("d")).select(group, "d.unit", "d.take")
        decided = done if decided is None else decided.unionByName(done)
        level = met.select(group, F.floor(F.col("slot") / chunk).alias("slot"), F.col("rest").alias("unit"))
    draw = F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.lit(-1), "unit.id", "unit.key"), 11) / F.lit(9007199254740992.0)
    return decided.unionByName(level.select(group, "unit", F.when(draw < F.col("unit.p"), 1).otherwise(0).cast("int").alias("take")))


def mix(docs: DataFrame, weights=WEIGHTS, share=SHARE, most=MOST_COPIES, seed: int = 7, chunk: int = CHUNK) -> DataFrame:
    """doc_id, key (hash of the row), source, size, source_size, target, copies of each document row."""
    sized = materialize(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("doc_id", "text", "source").alias("key"), F.col("source"), word_count(F.col("text")).alias("size")), "sizes")
    goal = materialize(targets(sized, weights, share, most), "targets")
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    goal = goal.withColumn("_whole", F.floor(ratio + 1e-12)).withColumn("_p", F.greatest(ratio - F.col("_whole"), F.lit(0.0)))
    goal = goal.withColumnRenamed("source", "_source")
    rows = sized.join(goal, sized["source"].eqNullSafe(goal["_source"])).drop("_source")
    parts = F.struct("source", "source_size", "target", "_whole")
    drawn = rows.where(F.col("_p") > 1e-12).select(
        parts.alias("part"),
        F.ceil(F.col("n_units") / chunk).alias("chunks"),
        F.struct("size", F.col("doc_id").alias("id"), "key", F.col("_p").alias("p")).alias("unit"),
    )
    rounded = round_copies(drawn, "part", seed, chunk).select(
        F.col("unit.id").alias("doc_id"), F.col("unit.key").alias("key"), "part.source", F.col("unit.size").alias("size"), "part.source_size", "part.target", (F.col("part._whole") + F.col("take")).alias("copies")
    )
    whole = rows.where(F.col("_p") <= 1e-12).select("doc_id", "key", "source", "size", "source_size", "target", F.col("_whole").alias("copies"))
    return rounded.unionByName(whole)


def apply_mix(docs: DataFrame, **options) -> DataFrame:
    """The documents, each row repeated as often as the mix takes it."""
    names = docs.columns
    copies = mix(docs, **options).groupBy("doc_id", "key").agg(F.sort_array(F.collect_list("copies")).alias("_copies")).withColumnRenamed("doc_id", "_id")
    keyed = docs.withColumn("_row", F.xxhash64("doc_id", "text", "source"))
    placed = keyed.withColumn("_place", F.row_number().over(Window.partitionBy("_row").orderBy("doc_id")))
    joined = placed.join(copies, (placed["_row"] == copies["key"]) & placed["doc_id"].cast("long").eqNullSafe(copies["_id"]))
    times = F.try_element_at("_copies", F.col("_place")).cast("int")
    return joined.where(times > 0).withColumn("_n", F.explode(F.sequence(F.lit(1), times))).select(*[placed[c] for c in names])
