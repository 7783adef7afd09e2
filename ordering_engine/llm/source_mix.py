"""Mixing sources to target weights with a low-discrepancy schedule.

Slot ``i`` of the schedule gets the point frac(i * golden ratio), taken in exact 32-bit integers;
the point falls into one source's share of the cumulative targets, so every stretch of the
schedule holds each source in proportion. A slot's rank within its source names the block of that
source it takes. Blocks are equal numbers of words: the source's documents, shuffled by a keyed
hash, laid end to end and cut into blocks of one slot's words; ranks past the last block start over.
A source's slots come within few blocks of its target; the rest is settled word by word: reading goes
on where its last slot ended, or stops that much earlier, so every source gets its target to the word.

Both running sums (words before a document, slots before a slot) go over buckets first and rows
second, so a source with a third of all rows is spread over all buckets and no task holds a source. Buckets are ranges of the
shuffle's hash, and there are as many as the rows ask for. Rows with equal id and text are numbered, per part of the table
first, and the number enters the hash, so repeated rows are spread as well. A slot finds its source among those of its
bin of the range. Windows over all sources hold one row a source.

Targets: every source gets its weight's share of the total, stops at ``max_epochs`` times its own
size, and the excess goes to the others by weight until none is above.

Defined results: null text has size 0; the null source is a source of its own, last in order; a
document without words is never taken; repeated rows are documents of their own; a null id is
allowed; an empty table gives an empty result; other columns are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import materialize

#: The golden ratio's fraction in 32 bits (odd, so the points are a permutation), and the range.
GOLDEN_32 = 2654435769
RANGE_32 = 1 << 32


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def source_targets(sized: DataFrame, weights: tuple[float, ...] = (1, 2, 3), max_epochs: int = 3) -> DataFrame:
    """From rows (_source, _size): one row per source with ``source_size`` and ``target``.

    Filling to a common level: with sources ordered by cap / weight, the first k are capped where
    the level of the rest is no lower than their ratio. One row per source enters these windows.
    """
    per = sized.groupBy("_source").agg(F.sum("_size").alias("source_size"))
    by_name = Window.orderBy(F.col("_source").asc_nulls_last())
    place = F.row_number().over(by_name) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (place % len(weights) + 1).cast("int"))
    per = per.withColumn("_place", place).withColumn("_weight", weight).withColumn("_cap", (F.col("source_size") * max_epochs).cast("double"))
    order = Window.orderBy(F.col("_cap") / F.col("_weight"), "_place")
    everything = Window.partitionBy()
    before, rest = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    total = F.sum("source_size").over(everything)
    level = (total - F.coalesce(F.sum("_cap").over(before), F.lit(0.0))) / F.sum("_weight").over(rest)
    per = per.withColumn("_level", level).withColumn("_capped", F.col("_cap") <= level * F.col("_weight"))
    final = F.coalesce(F.max(F.when(~F.col("_capped"), F.col("_level"))).over(everything), F.lit(0.0))
    return per.select("_source", "_place", "source_size", F.when(F.col("_capped"), F.col("_cap")).otherwise(final * F.col("_weight")).alias("target"))


def schedule(targets: DataFrame, block_words: int, chunk: int = 1 << 14) -> DataFrame:
    """The mix, slot by slot: ``slot``, ``_place`` (the source's), ``rank`` (0-based within the source)."""
    spark = targets.sparkSession
    total = targets.agg(F.sum("target")).first()[0] or 0.0
    n = int(-(-total // block_words))
    upper = Window.orderBy("_place").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    shares = targets.withColumn("_to", F.sum("target").over(upper) / F.lit(max(total, 1.0)) * RANGE_32)
    shares = shares.withColumn("_to", F.when(F.lead("_place").over(Window.orderBy("_place")).isNull(), F.lit(float(RANGE_32))).otherwise(F.col("_to")))
    shares = shares.withColumn("_from", F.coalesce(F.lag("_to").over(Window.orderBy("_place")), F.lit(0.0)))
    # Bins, a few for each source: a source is in the bins that its share touches, a slot in that of its point.
    bin_width = RANGE_32 >> min(30, max(8, (4 * targets.count()).bit_length()))
    bins = shares.where("_from < _to").select("_place", "_from", "_to", F.explode(F.expr(f"sequence(cast(_from AS bigint) div {bin_width}, cast(ceil(_to) - 1 AS bigint) div {bin_width})")).alias("_bin"))
    slots = spark.range(n).select(F.col("id").alias("slot"), ((F.col("id") * GOLDEN_32) % RANGE_32).alias("_point")).withColumn("_bin", F.expr(f"_point div {bin_width}"))
    slots = slots.join(bins, "_bin").where("_point >= _from AND _point < _to").select("slot", "_place")
    slots = slots.withColumn("_chunk", F.expr(f"slot div {chunk}"))
    per_chunk = slots.groupBy("_place", "_chunk").count()
    earlier = Window.partitionBy("_place").orderBy("_chunk").rowsBetween(Window.unboundedPreceding, -1)
    offsets = per_chunk.select("_place", "_chunk", F.coalesce(F.sum("count").over(earlier), F.lit(0)).alias("_before"))
    within = F.row_number().over(Window.partitionBy("_place", "_chunk").orderBy("slot")) - 1
    return slots.withColumn("_within", within).join(offsets, ["_place", "_chunk"]).select("slot", "_place", (F.col("_before") + F.col("_within")).alias("rank"))


def _numbered(sized: DataFrame) -> DataFrame:
    """``sized`` with ``_number``, 0.. among the rows of one ``_key``: places in a part of the table, after those of earlier parts."""
    rows = sized.withColumn("_row", F.monotonically_increasing_id()).withColumn("_part", F.shiftright("_row", 33))
    earlier = Window.partitionBy("_key").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    counts = rows.groupBy("_key", "_part").agg(F.count(F.lit(1)).alias("_n")).select(F.col("_key").alias("_k"), F.col("_part").alias("_p"), F.coalesce(F.sum("_n").over(earlier), F.lit(0)).alias("_first"))
    later = counts.where("_first > 0")
    place = F.row_number().over(Window.partitionBy("_key", "_part").orderBy("_row")) - 1
    found = rows.withColumn("_in", place).join(later, (F.col("_key") == F.col("_k")) & (F.col("_part") == F.col("_p")), "left")
    return found.withColumn("_number", F.col("_in") + F.coalesce("_first", F.lit(0))).drop("_row", "_part", "_in", "_k", "_p", "_first")


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[float, ...] = (1, 2, 3), max_epochs: int = 3, block_words: int = 256, bucket_rows: int = 1 << 16, seed: int = 0, shuffle_by: tuple[str, ...] | None = None) -> DataFrame:
    """One row per input row: id, ``size``, ``source_size``, ``target``, ``taken``.

    ``block_words`` are the words of one slot, whatever the corpus' size. A source's taken words are its target,
    rounded. ``seed`` keys the shuffle within sources, by the columns ``shuffle_by`` (id and text).
    """
    sized = docs.select(F.col(id_col).alias("_id"), F.col(source_col).alias("_source"), n_words(F.col(text_col)).alias("_size"), F.xxhash64(F.lit(seed), *(shuffle_by or (id_col, text_col))).alias("_key"))
    sized = materialize(sized, "mix-sized")
    targets = materialize(source_targets(sized, weights, max_epochs), "mix-targets")
    small = targets.select(F.col("_source").alias("_s"), "_place", "source_size", "target")
    bits = max(6, (sized.count() // bucket_rows).bit_length())
    rows = _numbered(sized).withColumn("_key", F.xxhash64("_key", "_number")).withColumn("_bucket", F.shiftrightunsigned("_key", 64 - bits))
    rows = materialize(rows.join(small, F.col("_source").eqNullSafe(F.col("_s"))).drop("_s", "_source"), "mix-rows")

    per_bucket = rows.groupBy("_place", "_bucket").agg(F.sum("_size").alias("_words"))
    earlier = Window.partitionBy("_place").orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = per_bucket.select("_place", "_bucket", F.coalesce(F.sum("_words").over(earlier), F.lit(0)).alias("_before"))
    order = Window.partitionBy("_place", "_bucket").orderBy("_key", "_id")
    placed = rows.withColumn("_inner", F.coalesce(F.sum("_size").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).withColumn("_order", F.row_number().over(order))
    placed = placed.join(offsets, ["_place", "_bucket"]).withColumn("_start", F.col("_before") + F.col("_inner"))
    placed = materialize(placed.select("_id", "_place", "_size", "source_size", "target", "_bucket", "_order", "_start"), "mix-placed")

    # Blocks that the schedule asks for, and how often: ranks past a source's last block start over.
    sizes = targets.select("_place", "source_size")
    asked = schedule(targets, block_words).join(sizes, "_place").where("source_size > 0")
    asked = asked.withColumn("_block", F.expr(f"rank % ((source_size + {block_words} - 1) div {block_words})"))
    asked = materialize(asked.groupBy("_place", "_block").agg(F.count(F.lit(1)).alias("_times"), F.first("source_size").alias("_of")), "mix-asked")
    lies_in = F.expr(f"explode(sequence(_start div {block_words}, (_start + _size - 1) div {block_words}))")
    pieces = placed.where("_size > 0").select("_place", "_bucket", "_order", "_start", "_size", lies_in.alias("_block"))
    overlap = F.expr(f"least(_start + _size, (_block + 1) * {block_words}) - greatest(_start, _block * {block_words})")
    taken = pieces.join(asked.drop("_of"), ["_place", "_block"]).groupBy("_place", "_bucket", "_order").agg(F.sum(overlap * F.col("_times")).alias("_scheduled"))

    # What the slots read of each source, and what its target asks for: the words between the two are added or left out.
    block = F.expr(f"least({block_words}, _of - _block * {block_words})")
    read = asked.groupBy("_place").agg(F.sum(block * F.col("_times")).alias("_read"))
    read = targets.select("_place", F.round("target").cast("long").alias("_due")).join(read, "_place", "left").select("_place", "_due", F.coalesce("_read", F.lit(0)).alias("_read"))
    among = lambda first: F.expr(f"IF(_size = 0, 0, {first} div source_size * _size + greatest(0, least(_size, {first} % source_size - _start)))")
    settled = placed.join(F.broadcast(read), "_place").join(taken, ["_place", "_bucket", "_order"], "left")
    settled = settled.withColumn("taken", F.coalesce("_scheduled", F.lit(0)) + among("_due") - among("_read"))
    return settled.select(F.col("_id").alias(id_col), F.col("_size").alias("size"), "source_size", "target", F.col("taken").cast("long").alias("taken"))


def mixed_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **options) -> DataFrame:
    """``docs`` as the mix takes them: each row as many times as its taken words go into its size, rounded; a row without words stays once."""
    # The documents' own columns stay in one, so that none can clash with those of the mix.
    numbered = docs.select(F.struct("*").alias("_doc"), F.col(id_col).alias("_id"), F.col(text_col).alias("_text"), F.col(source_col).alias("_source"))
    numbered = materialize(numbered.withColumn("_mix_row", F.monotonically_increasing_id()), "mix-docs")
    counted = mix(numbered, "_mix_row", "_text", "_source", shuffle_by=("_id", "_text"), **options)
    times = F.when(F.col("size") == 0, F.lit(1)).otherwise(F.round(F.col("taken") / F.col("size")).cast("int"))
    counted = counted.select(F.col("_mix_row").alias("_row"), times.alias("_times")).where("_times > 0")
    joined = numbered.join(counted, F.col("_mix_row") == F.col("_row"))
    return joined.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_times")))).select("_doc.*")
