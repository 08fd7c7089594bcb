"""Sharding by balanced label propagation. DataFrame functions only.

Documents with equal texts are linked, each to all of its group, which a count per (group, shard) stands for. Labels start as hashes. In each
round a linked document asks to move to the shard that holds most of its group among those with room (by the counts,
joined back); requests are granted in hash order up to the shard's free places. Shards have quotas of rows that differ by one at most,
so no round can overfill one, and a group larger than a quota fills shards one after the other. Rounds end when
none is granted or after `ROUNDS`. Documents without links have no neighbours to move to; they fill the places
left, so the law is `rows`: counts differ by one at most. Ranks come from two-level prefix sums, so a hot group, shard or
text is no single task. All hashes and orders go by doc_id, text and the number of a repeated row, so neither the order of the rows nor the
layout of the files matters.

Defined results: a null text counts as an empty one (size 8, crc32 0) and is linked to empty ones; rows that repeat an id are
documents of their own; fewer documents than shards fill the first shards; an empty table gives an empty table; extra columns are not
read. grown_shard is null: the law is not `key`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farfield.llm.common import Generations, bucketed_rank, written

SHARDS = 24
#: A round fills one shard for a group, so a group over many shards needs as many rounds.
ROUNDS = SHARDS
BUCKETS = 256


def _spread(*columns: str) -> Column:
    return F.pmod(F.xxhash64(*columns), F.lit(BUCKETS)).cast("int")


def prepared(docs: DataFrame) -> DataFrame:
    """rid, doc_id, size, text_crc32, g (hash of the text), linked. rid is unique and hangs on doc_id, text and, among rows alike in both, a number."""
    bytes_ = F.encode(F.coalesce(F.col("text").cast("string"), F.lit("")), "utf-8")
    rows = written(
        docs.select(
            F.monotonically_increasing_id().alias("row"), "doc_id", (F.octet_length(bytes_) + 8).cast("long").alias("size"),
            F.crc32(bytes_).alias("text_crc32"), F.md5(bytes_).alias("g"),
        ),
        "shard-rows",
    )
    groups = rows.groupBy("g").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select(F.reverse("g").alias("k"))
    # joined by the reversed hash, so that both sides are exchanges and a hot group can be split
    known = rows.withColumn("k", F.reverse("g")).join(groups.withColumn("linked", F.lit(True)), "k", "left").select(
        F.md5(F.concat_ws("/", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), "g")).alias("alike"), "row", "doc_id", "size", "text_crc32", "g", F.coalesce("linked", F.lit(False)).alias("linked")
    )
    known = written(known, "shard-known")
    # rows alike in id and text can change places, so any order will do; rows without links have no such
    repeats = bucketed_rank(known.filter("linked"), "alike", [F.col("row")], _spread("row"), "nth")
    single = known.filter("NOT linked").withColumn("nth", F.lit(0).cast("long"))
    return repeats.unionByName(single).select(F.concat_ws("/", "alike", "nth").alias("rid"), "doc_id", "size", "text_crc32", "g", "linked")


def propagate(linked: DataFrame, quota: list[int], rounds: int = ROUNDS) -> DataFrame:
    """(rid, g, shard): labels after the rounds. quota: rows that each shard may hold."""
    n = len(quota)
    at = lambda values, shard: F.element_at(F.array(*map(F.lit, values)), shard + 1)
    # the start: by hash, cut to the quotas like any other move
    start = linked.select("rid", "g", F.pmod(F.xxhash64("rid", F.lit("start")), F.lit(n)).cast("int").alias("shard"))
    tables = Generations("labels")
    state = tables.written(start)
    for r in range(rounds):
        load = {x["shard"]: x["n"] for x in state.groupBy("shard").agg(F.count(F.lit(1)).alias("n")).collect()}  # one row a shard
        room = [max(0, quota[s] - load.get(s, 0)) for s in range(n)]
        held = state.groupBy("g", "shard").agg(F.count(F.lit(1)).alias("n"))
        # n rows per group at most; a full shard attracts no one, and keeps its own
        best = held.withColumn("open", at(room, F.col("shard")) > 0).groupBy("g").agg(
            F.max(F.when(F.col("open"), F.struct("n", F.xxhash64("g", "shard").alias("h"), "shard"))).alias("to"), F.count(F.lit(1)).alias("spread")
        )
        best = best.filter("spread > 1 AND to IS NOT NULL").select(F.reverse("g").alias("k"), F.col("to.shard").alias("to"), F.col("to.n").alias("there"))
        own = state.withColumn("k", F.reverse("g"))
        fuller = held.select(F.concat_ws("/", F.reverse("g"), "shard").alias("gs"), F.col("n").alias("here"))
        asked = own.join(best, "k").filter("shard <> to").withColumn("gs", F.concat_ws("/", "k", "shard"))
        # neighbours at home that outnumber those at the goal are no reason to leave
        asked = asked.join(fuller, "gs").filter("there >= here")
        asked = asked.select("rid", "to", F.xxhash64("rid", F.lit(r)).alias("h"))
        ranked = bucketed_rank(asked, "to", [F.col("h"), F.col("rid")], F.pmod(F.shiftright("h", 48), F.lit(BUCKETS)), "nth")
        granted = ranked.filter(F.col("nth") < at(room, F.col("to"))).select(F.col("rid").alias("m"), "to")
        moved = tables.written(state.join(granted, state["rid"] == granted["m"], "left").select("rid", "g", F.coalesce("to", "shard").alias("shard"), F.col("to").isNotNull().alias("moved")))
        state = moved.select("rid", "g", "shard")
        if moved.filter("moved").isEmpty():
            break
    return state


def shards_of(docs: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS) -> DataFrame:
    """rid, doc_id, size, text_crc32, g, shard."""
    rows = written(prepared(docs), "shard-rows")
    n = rows.count()
    quota = [n // shards + (s < n % shards) for s in range(shards)]
    linked = rows.filter("linked")
    labels = propagate(linked, quota, rounds)
    # What the hash start put above a quota gives way, then the rest fills the places left.
    ranked = bucketed_rank(labels, "shard", [F.xxhash64("rid"), F.col("rid")], _spread("rid"), "nth")
    quotas = F.array(*map(F.lit, quota))
    stays = written(ranked.filter(F.col("nth") < F.element_at(quotas, F.col("shard") + 1)).select(F.col("rid").alias("m"), F.col("shard").alias("label")), "labels")
    load = {x["label"]: x["n"] for x in stays.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    ends, total = [], 0
    for s in range(shards):
        total += quota[s] - load.get(s, 0)
        ends.append(total)
    joined = rows.join(stays, rows["rid"] == stays["m"], "left").drop("m")
    loose = joined.filter("label IS NULL").withColumn("one", F.lit(0))
    loose = bucketed_rank(loose, "one", [F.xxhash64("rid"), F.col("rid")], F.pmod(F.xxhash64("rid", F.lit(1)), F.lit(4 * BUCKETS)), "nth")
    shard = F.size(F.filter(F.array(*map(F.lit, ends)), lambda e: e <= F.col("nth")))
    filled = loose.withColumn("label", shard).drop("one", "nth")
    return joined.filter("label IS NOT NULL").unionByName(filled).withColumnRenamed("label", "shard")


def op6_label_propagation(docs: DataFrame) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard."""
    rows = written(shards_of(docs), "shards")
    placed = bucketed_rank(rows, "shard", [F.col("doc_id"), F.col("rid")], _spread("rid"), "slot")
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.col("shard").cast("int").alias("shard"), F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def cut_links(sharded: DataFrame) -> DataFrame:
    """One row: linked (documents beyond the first of their group), cut (those outside the group's fullest shard beyond need)."""
    held = sharded.groupBy("g", "shard").agg(F.count(F.lit(1)).alias("n"))
    groups = held.groupBy("g").agg(F.sum("n").alias("n"), F.max("n").alias("most"))
    return groups.filter("n > 1").agg(F.sum(F.col("n") - 1).alias("linked"), F.sum(F.col("n") - F.col("most")).alias("cut"))
