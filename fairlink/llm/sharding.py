"""Shards by balanced label propagation, with exactly equal row counts.

Equal texts form a group; its members are linked through the group as through a hub, so that no
pair is ever written. What the iteration holds are pieces: the members of one group that one hash of
doc_id put into one shard at the start, at most as many per group as there are shards, however large a group
is. A fragment is all pieces of a group that sit in one shard now. Each round is a set of joins: a group's
fragments are its members' neighbourhood; the shard where most members could lie together, by what lies there
and by the room left, is what the group's other fragments ask for; quotas limit what a shard may take in
beyond its capacity, and requests of large gain go first, by classes of gain, the last class by a hashed share
of its fragments. Rounds end after ROUNDS. Texts that
occur once have no links; they take no room in the rounds, for they can lie anywhere.

A group larger than a shard cannot lie together: such groups, fewer than there are shards, are laid side by
side over the first shards before the rounds, and take that room from them.

Then the counts are made exact (law `rows`, sizes differ by one at most): each shard keeps the groups that
the rounds brought together in it, up to its exact count; single documents fill it where they began. Groups that the quotas
left in several shards, and what is beyond a count, go to the shards that have room, groups first and side by
side, then singles. So a group that fits a shard is cut only where its shard holds more rows of groups than its
count, or at the end of a shard's room: less often than there are shards. Ranks come from counts per bucket and ranks in a
bucket; a large group's rows are spread over buckets of their own by a hash of doc_id, and no bucket needs all
rows of a group.

Null texts are empty texts, alike to each other. Repeated doc_ids are ranked among themselves by
the digest of the text; rows that are equal in all of it take the ranks in any order, which no output shows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fairlink.llm.common import durable, text_or_empty

SHARDS = 24
ROUNDS = 4
SLACK = 0.05
BUCKET_ROWS = 20_000
#: Labels beside the shards: groups larger than a shard, and groups that the rounds left in several.
GIANT, SPLIT = -2, -1


def _hash(*columns: Column, into: int | Column) -> Column:
    return F.pmod(F.xxhash64(*columns), F.lit(into) if isinstance(into, int) else into)


def propagate(pieces: DataFrame, capacity: list[float], rounds: int = ROUNDS) -> DataFrame:
    """(grp, origin, shard, n) pieces after balanced label propagation; capacity: of each shard."""
    most = F.get(F.array(*map(F.lit, capacity)), F.col("shard"))
    state = pieces
    for turn in range(rounds):
        held = state.groupBy("shard").agg(F.sum("n").alias("held"))  # as many rows as shards
        fragments = state.groupBy("grp", "shard").agg(F.sum("n").alias("n"))
        sizes = state.groupBy("grp").agg(F.sum("n").alias("size"))
        known = fragments.join(sizes, "grp").join(F.broadcast(held), "shard")
        reach = F.col("n") + F.least(F.col("size") - F.col("n"), F.greatest(F.lit(0.0), most - F.col("held")))
        best = known.groupBy("grp").agg(F.max(F.struct(reach.alias("reach"), F.col("n"), F.xxhash64("grp", "shard").alias("tie"), F.col("shard").alias("to"))).alias("b"))
        asked = state.join(best, "grp").select(
            *("grp", "origin", "shard", "n"),
            F.col("b.to").alias("to"),
            F.floor(F.log2(F.col("b.n").cast("double"))).cast("int").alias("gain"),
            _hash(F.col("grp"), F.col("shard"), F.lit(turn), into=1 << 20).alias("share"),
        )
        # What each shard may take: its room plus half of what would leave it; classes of gain in turn.
        moving = F.col("to") != F.col("shard")
        inflow = asked.where(moving).groupBy("to", "gain").agg(F.sum("n").alias("wanted"))
        outflow = asked.where(moving).groupBy("shard").agg(F.sum("n").alias("leaving"))
        room = held.join(outflow, "shard", "left").select(F.col("shard").alias("to"), (most - F.col("held") + F.coalesce("leaving", F.lit(0)) / 2).alias("room"))
        order = Window.partitionBy("to").orderBy(F.desc("gain")).rowsBetween(Window.unboundedPreceding, -1)
        quota = (
            inflow.join(room, "to", "left")
            .withColumn("left", F.col("room") - F.coalesce(F.sum("wanted").over(order), F.lit(0)))
            .select("to", "gain", F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.col("left") / F.col("wanted"))).alias("granted"))
        )  # shards times classes of gain: at most 64 rows a shard
        state = durable(
            asked.join(F.broadcast(quota), ["to", "gain"], "left").select(
                *("grp", "origin", "n"), F.when(moving & (F.col("share") < F.col("granted") * (1 << 20)), F.col("to")).otherwise(F.col("shard")).alias("shard")
            )
        )
    return state


def shard(docs: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS, slack: float = SLACK) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot and grown_shard of every row."""
    text = text_or_empty()
    rows = docs.select("doc_id", (F.octet_length(text) + 8).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.md5(text.cast("binary")).alias("digest"))
    rows = rows.withColumn("grp", F.xxhash64("digest")).withColumn("origin", _hash(F.col("doc_id"), F.lit("first"), into=shards).cast("int"))
    total = rows.count()
    base, rest = divmod(total, shards)
    pieces = rows.groupBy("grp", "origin").agg(F.count("*").alias("n"))
    sizes = pieces.groupBy("grp").agg(F.sum("n").alias("members")).where("members > 1")
    linked = durable(pieces.join(sizes, "grp").select("grp", "origin", F.col("origin").alias("shard"), "n", "members"))
    giant = F.col("members") > base
    wide = linked.where(giant).agg(F.sum("n")).first()[0] or 0
    exact = [base + (s < rest) for s in range(shards)]
    taken = [min(exact[s], max(0, wide - sum(exact[:s]))) for s in range(shards)]
    moved = propagate(linked.where(~giant).drop("members"), [(1 + slack) * total / shards - t for t in taken], rounds)
    # The label of a piece: where the rounds brought its group together. Singles stay where they began.
    where = moved.groupBy("grp").agg(F.min("shard").alias("low"), F.max("shard").alias("high"), F.sum("n").alias("members"))
    where = where.select("grp", F.when(F.col("low") == F.col("high"), F.col("low")).otherwise(SPLIT).alias("label"), "members")
    large = linked.where(giant).select("grp", F.lit(GIANT).alias("label"), "members").distinct()
    label = linked.select("grp", "origin").join(where.unionByName(large), "grp")
    placed = rows.join(label, ["grp", "origin"], "left")
    kind = F.col("members").isNull().cast("int")
    heavy = F.coalesce("members", F.lit(1)) > BUCKET_ROWS
    spread = F.ceil(F.coalesce("members", F.lit(1)) / BUCKET_ROWS)
    many = max(1, total // (shards * BUCKET_ROWS))
    placed = (
        placed.withColumn("kind", kind)
        .withColumn("label", F.coalesce("label", "origin"))
        .withColumn("lot", _hash(F.col("grp"), F.lit("lot"), into=many).cast("int"))
        .withColumn("own", F.when(heavy, F.col("grp")).otherwise(0))
        .withColumn("part", F.when(heavy, _hash(F.col("doc_id"), F.lit("part"), into=spread)).otherwise(0).cast("int"))
    )
    key = ["label", "kind", "lot", "own", "part"]
    buckets = placed.groupBy(*key).agg(F.count("*").alias("rows"))
    within = Window.partitionBy("label").orderBy(*key[1:]).rowsBetween(Window.unboundedPreceding, -1)
    offsets = buckets.select(*key, F.coalesce(F.sum("rows").over(within), F.lit(0)).alias("before"))
    # Of each shard its count less what giants take, and what begins there: as many rows as shards, and one of split groups.
    spans = docs.sparkSession.createDataFrame([*zip(range(shards), exact, taken, strict=True), (SPLIT, 0, 0)], "label int, exact long, taken long").withColumn("exact", F.col("exact") - F.col("taken"))
    held = buckets.groupBy("label").agg(F.sum("rows").alias("all"), F.sum(F.when(F.col("kind") == 0, F.col("rows")).otherwise(0)).alias("grouped"))
    spans = spans.join(F.broadcast(held), "label", "left").select("label", "exact", "taken", F.coalesce("all", F.lit(0)).alias("all"), F.coalesce("grouped", F.lit(0)).alias("grouped"))
    beyond = lambda c: F.greatest(F.lit(0), F.col(c) - F.col("exact"))
    spans = spans.select("*", beyond("grouped").alias("torn"), (beyond("all") - beyond("grouped")).alias("loose"), F.greatest(F.lit(0), F.col("exact") - F.col("all")).alias("spare"))
    ahead = Window.orderBy("label").rowsBetween(Window.unboundedPreceding, -1)
    until = lambda c: F.coalesce(F.sum(c).over(ahead), F.lit(0))
    spans = spans.select("*", until("torn").alias("torn_before"), (F.sum("torn").over(Window.partitionBy()) + until("loose")).alias("loose_before"), until("spare").alias("spare_before"))
    # Of the shards with room, in order: where it begins, in the order of the rows that fill it.
    holes = spans.agg(F.array_sort(F.collect_list(F.when(F.col("spare") > 0, F.struct("spare_before", "spare", F.col("label").alias("to"), (F.col("taken") + F.col("all")).alias("filled"))))).alias("holes"))
    rank = F.row_number().over(Window.partitionBy(*key).orderBy("grp", "digest", "doc_id")) - 1
    ranked = placed.withColumn("rank", rank).join(offsets, key).withColumn("place", F.col("before") + F.col("rank"))
    known = ranked.join(F.broadcast(spans), "label", "left").crossJoin(F.broadcast(holes))
    stays = F.col("place") < F.col("exact")
    queue = F.when(F.col("kind") == 0, F.col("torn_before") + F.col("place") - F.col("exact")).otherwise(F.col("loose_before") + F.col("place") - F.greatest("exact", "grouped"))
    known = known.withColumn("queue", queue).withColumn("hole", F.get(F.filter("holes", lambda h: (h["spare_before"] <= F.col("queue")) & (F.col("queue") < h["spare_before"] + h["spare"])), 0))
    border = rest * (base + 1)
    early = F.col("place") < border
    run = F.when(early, F.expr(f"place div {base + 1}")).otherwise(F.expr(f"{rest} + (place - {border}) div {max(1, base)}"))
    step = F.when(early, F.expr(f"place % {base + 1}")).otherwise(F.expr(f"(place - {border}) % {max(1, base)}"))
    laid = F.col("label") == GIANT
    return known.select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("rows").alias("law"),
        F.when(laid, run).when(stays, F.col("label")).otherwise(F.col("hole.to")).cast("int").alias("shard"),
        F.when(laid, step).when(stays, F.col("taken") + F.col("place")).otherwise(F.col("hole.filled") + F.col("queue") - F.col("hole.spare_before")).cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )
