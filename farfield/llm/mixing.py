"""Mixing sources to target weights, by fixed-length blocks of words. DataFrame functions only.

1. Targets: source weights share `SHARE` times all words; no source gets over `MOST` times its own words, and what is cut off
   is shared again by weight until none is above.
2. Packing: the documents of a source, in pseudorandom order, are one stream of words, cut into blocks of `BLOCK` words (the last one may
   be short). The places come from two-level prefix sums, so a hot source is no single task.
3. Counts: each source gets as many slots as bring its target. How many of them each of the `SHARDS` output shards gets is a multinomial draw, one table
   row for each source and shard. The totals are fixed: if the sources of a shard were drawn instead, small sources would miss their targets
   by several per cent. A shard's slots of a source are a run of the source's slot numbers, as long as the count that was drawn.
4. Slot k of a source is block p(k mod n) of epoch k div n, where p is a pseudorandom permutation of its n blocks for each epoch, from
   swap-or-not rounds. No list is shuffled or kept. Slots and blocks are joined by (source, block).

A block comes once per epoch at most and there are `MOST` epochs at most, so no document is taken over `MOST` times its size.

Defined results: a null text has size 0, a null source is a source of its own and comes last by code point; rows that repeat an id are
documents of their own; sources without words get target 0; an empty table gives an empty table; extra columns are not read. Draws
hang on values and hashes only, so reruns agree, except that identical rows may swap places.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farfield.llm.common import bitmaps, bucketed_rank, has_bit, n_words, written

#: Weights of the sources by code point, repeating.
WEIGHTS = (5, 2, 1)
SHARE, MOST = 1.5, 2
BLOCK = 128
SEED = 17
ROUNDS = 24
SHARDS = 64
#: Documents of a source are ordered within so many hash buckets; slots are made in runs of so many.
BUCKETS, RUN = 1024, 4_096


def sized(docs: DataFrame, *more: str) -> DataFrame:
    """A written table with a row number `rid`, doc_id, source, size and more."""
    return written(
        docs.select(
            F.monotonically_increasing_id().alias("rid"), F.col("doc_id"), F.col("source").cast("string").alias("source"), n_words(F.col("text").cast("string")).alias("size"), *more
        ),
        "sizes",
    )


def targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, most: float = MOST, block: int = BLOCK) -> DataFrame:
    """source, source_size, target, n_blocks, n_slots.

    Filling up: with the sources by cap / weight, those before some place are at their caps, and the rest share what is left by
    weight. The place is the first whose share stays under its own cap.
    """
    by_source = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    nth = F.row_number().over(Window.orderBy(F.asc_nulls_last("source"))) - 1
    weighed = by_source.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (nth % len(weights)).cast("int") + 1).cast("double"))
    weighed = weighed.withColumn("cap", most * F.col("source_size"))
    order = Window.orderBy(F.col("cap") / F.col("weight"), F.asc_nulls_last("source"))
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    rest = order.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    every = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    level = (share * F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(rest)
    leveled = weighed.withColumn("level", level).withColumn("fits", F.col("level") <= F.col("cap") / F.col("weight"))
    # the level rises from place to place until the first that fits, which has the level for all behind it
    final = F.min(F.when(F.col("fits"), F.struct(F.col("cap") / F.col("weight"), "source", "level"))).over(every)["level"]
    full = F.coalesce(final, F.lit(float("inf")))
    chosen = leveled.withColumn("target", F.least("cap", full * F.col("weight")).cast("double"))
    n_blocks = F.ceil(F.col("source_size") / block).cast("long")
    mean = F.col("source_size") / F.col("n_blocks")
    return chosen.withColumn("n_blocks", n_blocks).select(
        "source", "source_size", "target", "n_blocks",
        F.when(F.col("n_blocks") > 0, F.least(F.round(F.col("target") / mean).cast("long"), F.floor(most * F.col("n_blocks")).cast("long"))).otherwise(0).cast("long").alias("n_slots"),
    )


def permuted(x: Column, n: Column, key: Column, rounds: int = ROUNDS) -> Column:
    """A pseudorandom permutation of 0..n-1 for each key: each round pairs x with its mirror about a random place and swaps by a random bit."""

    def one(x: Column, r: Column) -> Column:
        mirror = F.pmod(F.xxhash64(key, r, F.lit("place")) - x, n)
        swap = F.pmod(F.xxhash64(key, r, F.greatest(x, mirror)), F.lit(2)) == 1
        return F.when(swap, mirror).otherwise(x)

    return F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), x, one)


def packed(sizes: DataFrame, block: int = BLOCK, seed: int = SEED) -> DataFrame:
    """rid, source, start, block, words: how many of a document's words lie in each block that it touches."""
    bucket = F.pmod(F.xxhash64("doc_id", "size", F.lit(seed)), F.lit(BUCKETS)).cast("int")
    full = sizes.filter("size > 0").select("rid", "doc_id", "source", "size", bucket.alias("bucket"))
    by_bucket = full.groupBy("source", "bucket").agg(F.sum("size").alias("n"))
    upto = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    first = by_bucket.select(F.col("source").alias("s"), F.col("bucket").alias("b"), F.coalesce(F.sum("n").over(upto), F.lit(0)).alias("first"))
    own = Window.partitionBy("source", "bucket").orderBy(F.xxhash64("doc_id", F.lit(seed)), "doc_id", "size", "rid").rowsBetween(Window.unboundedPreceding, -1)
    placed = full.withColumn("within", F.coalesce(F.sum("size").over(own), F.lit(0)))
    placed = placed.join(first, placed["source"].eqNullSafe(first["s"]) & (placed["bucket"] == first["b"]))
    placed = placed.withColumn("start", F.col("first") + F.col("within"))
    last = F.floor((F.col("start") + F.col("size") - 1) / block)
    touched = placed.select("rid", "source", "size", "start", F.explode(F.sequence(F.floor(F.col("start") / block), last)).alias("block"))
    end = F.least(F.col("start") + F.col("size"), (F.col("block") + 1) * block)
    return touched.withColumn("words", end - F.greatest("start", F.col("block") * block)).select("rid", "source", "start", "block", "words")


def _runs(rows: DataFrame, n: str, *keys: str) -> DataFrame:
    """The rows once for each run of at most RUN of their n, as (keys, run), spread over tasks: a hot source has many runs."""
    runs = rows.filter(F.col(n) > 0).select(*rows.columns, F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col(n) - 1) / RUN))).alias("run"))
    # The number is named, as runs are few bytes and would be brought together in one task again.
    return runs.repartition(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), *keys, "run")


def _of_run(n: str) -> Column:
    return F.explode(F.sequence(F.col("run") * RUN, F.least((F.col("run") + 1) * RUN, F.col(n)) - 1))


def shard_counts(goals: DataFrame, shards: int = SHARDS, seed: int = SEED) -> DataFrame:
    """A written table, one row for each source and shard that got any: source, n_blocks, shard, n, first. n is the shard's multinomial count of the source's
    slots: as many trials as the source has slots, equal odds. The shard's slots are first .. first + n - 1."""
    tried = _runs(goals, "n_slots", "source").select("source", "n_blocks", _of_run("n_slots").alias("trial"))
    drawn = tried.withColumn("shard", F.pmod(F.xxhash64("source", "trial", F.lit(seed + 1)), F.lit(shards)).cast("int"))
    counts = drawn.groupBy("source", "n_blocks", "shard").agg(F.count(F.lit(1)).alias("n"))
    upto = Window.partitionBy("source").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    return written(counts.withColumn("first", F.coalesce(F.sum("n").over(upto), F.lit(0))), "shard-counts")


def slots(counts: DataFrame, seed: int = SEED) -> DataFrame:
    """source, slot, shard, epoch, block: every slot that the drawn counts give to a shard."""
    one = _runs(counts, "n", "source", "shard").select("source", "n_blocks", "shard", "first", _of_run("n").alias("place"))
    numbered = one.withColumn("slot", F.col("first") + F.col("place"))
    keyed = numbered.withColumn("epoch", F.floor(F.col("slot") / F.col("n_blocks")).cast("int")).withColumn("key", F.xxhash64("source", "epoch", F.lit(seed)))
    return keyed.select("source", "slot", "shard", "epoch", permuted(F.pmod("slot", F.col("n_blocks")), F.col("n_blocks"), F.col("key")).alias("block"))


def taken_pieces(sizes: DataFrame, counts: DataFrame) -> DataFrame:
    """rid, start, block, words, epoch, shard, slot: the blocks of the mix joined with the documents that they hold."""
    of = slots(counts).withColumnsRenamed({"source": "s", "block": "b"})
    pieces = packed(sizes)
    # Both sides grow with the corpus. What generates the slots is small, and Spark would take them for small too and broadcast them.
    return pieces.hint("merge").join(of.hint("merge"), pieces["source"].eqNullSafe(of["s"]) & (pieces["block"] == of["b"])).select("rid", "source", "start", "block", "words", "epoch", "shard", "slot")


def placed_slots(counts: DataFrame) -> DataFrame:
    """Slots with their place in the shard, from 0 without gaps, in which the sources are mixed."""
    drawn = slots(counts).withColumn("h", F.xxhash64("source", "slot", F.lit("place")))
    return bucketed_rank(drawn, "shard", [F.col("h"), F.col("source"), F.col("slot")], F.pmod(F.shiftright("h", 54), F.lit(BUCKETS)), "place").drop("h")


def op5_mixing(docs: DataFrame) -> DataFrame:
    """doc_id, size, source_size, target, taken, and shards: the output shards that hold words of the document."""
    sizes = sized(docs)
    goals = written(targets(sizes), "targets")
    # SHARDS are 64, so that a set of them is a long
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("shard"))
    taken = taken_pieces(sizes, shard_counts(goals)).groupBy(F.col("rid").alias("r")).agg(F.sum("words").alias("taken"), F.bit_or(bit).alias("set"))
    known = goals.select(F.col("source").alias("s"), "source_size", "target")
    # the few sources and their totals against many rows: Spark can split a hot source, as both sides are shuffled or one is small
    whole = sizes.join(known, sizes["source"].eqNullSafe(known["s"]))
    held = F.filter(F.sequence(F.lit(0), F.lit(SHARDS - 1)), lambda k: F.getbit(F.coalesce("set", F.lit(0).cast("long")), k) == 1)
    return whole.join(taken, F.col("rid") == F.col("r"), "left").select(
        "doc_id", "size", F.col("source_size").cast("long").alias("source_size"), "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"), held.alias("shards")
    )


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline: for each epoch in which a document is taken, a row with the words that the shards took; whole if all were. Null and shared doc_ids and
    null texts are rows like any other, by row ids; a text without words is in no block, so it is not taken."""
    sizes = sized(docs, "text", "lang")
    goals = written(targets(sizes), "targets")
    got = taken_pieces(sizes, shard_counts(goals)).withColumn("nth", F.col("block") - F.floor(F.col("start") / BLOCK))
    n = got.groupBy("rid", "epoch").agg(F.sum("words").alias("taken"), F.first("start").alias("start"))
    flags = bitmaps(got, ["rid", "epoch"], "nth").withColumnsRenamed({"rid": "r", "epoch": "e"})
    picked = n.join(flags, (F.col("rid") == F.col("r")) & (F.col("epoch") == F.col("e"))).select("r", "e", "taken", "start", "bits")
    words = F.regexp_extract_all("text", F.lit(r"([^\x20\x09-\x0D]+[\x20\x09-\x0D]*)"), F.lit(1))
    block_of = lambda i: F.floor((F.col("start") + i) / BLOCK) - F.floor(F.col("start") / BLOCK)
    part = F.regexp_replace(F.array_join(F.filter(words, lambda _, i: has_bit(F.col("bits"), block_of(i))), ""), r"[\x20\x09-\x0D]+\z", "")
    rows = sizes.join(picked, F.col("rid") == F.col("r"))
    mixed = rows.select("doc_id", F.when(F.col("taken") == F.col("size"), F.col("text")).otherwise(part).alias("text"), "lang", "source")
    return mixed.withColumn("n_chars", F.length("text").cast("long"))
