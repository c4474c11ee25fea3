"""Mixing sources to target weights, in DataFrame operations alone.

The words of each source are packed, document after document, into blocks of a fixed length. The output is a
row of shards with a fixed number of slots each; every shard draws how many of its slots each source fills
(the whole parts of the expected counts are given, the rest is a multinomial draw). A source's slots run
through pseudorandom permutations of its block numbers, one permutation a pass, and blocks are joined by number.

All draws are digests of (seed, place), so reruns agree whatever the partitions are.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from biclique_spark.llm.common import WORD, small, unused, written

#: Documents in a bucket of the two-level running sum; buckets of the draws' lookup; rounds of the permutation;
#: shards whose counts are summed in one group.
BUCKET_ROWS, LOOKUP, ROUNDS = 1024, 256, 6
SHARDS_A_SUM = 1024
#: Slots that a task makes about; few rows become many here, so the number of tasks is given.
SLOTS_A_TASK = 1 << 16


def uniform(*parts: Column) -> Column:
    """A number from 0 up to 1 (not included) from a digest of the parts."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *parts)), 1, 13), 16, 10).cast("double") / F.lit(float(1 << 52))


@dataclass
class Mix:
    """sources: one row a source. pieces: which words of which document lie in which block. slots: what the output holds."""

    sizes: DataFrame
    sources: DataFrame
    pieces: DataFrame
    slots: DataFrame
    shard_counts: DataFrame
    length: int


def word_sizes(docs: DataFrame, id_col: str, text_col: str, source_col: str) -> DataFrame:
    return docs.select(
        F.col(id_col).alias("doc_id"),
        F.when(F.col(source_col).isNull(), "").otherwise(F.concat(F.lit("="), F.col(source_col))).alias("source_key"),
        F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
    )


def targets(sizes: DataFrame, weights: tuple[int, ...], most: float) -> DataFrame:
    """source_key, source_size, weight, target. All words are shared by weight; no source gets more than ``most``
    times its size, and what it can't take goes to the others by weight. The level at which this comes to rest is
    found by one running sum over the sources in order of cap / weight."""
    by_name = Window.orderBy(F.col("source_key") == "", "source_key")
    rows = sizes.groupBy("source_key").agg(F.sum("size").alias("source_size"))
    rows = rows.withColumn(
        "weight", F.get(F.array(*map(F.lit, weights)), ((F.row_number().over(by_name) - 1) % len(weights)).cast("int"))
    ).withColumn("cap", F.col("source_size") * F.lit(float(most)))
    by_room = Window.orderBy(F.col("cap") / F.col("weight"), "source_key")
    everything = Window.partitionBy()
    rows = rows.withColumn(
        "level",
        (F.sum("source_size").over(everything) - F.sum("cap").over(by_room) + F.col("cap"))
        / (F.sum("weight").over(everything) - F.sum("weight").over(by_room) + F.col("weight")),
    ).withColumn("level", F.min(F.when(F.col("cap") / F.col("weight") >= F.col("level"), F.struct(F.col("cap") / F.col("weight"), F.col("source_key"), F.col("level")))).over(everything)["level"])
    target = F.least("cap", F.coalesce(F.col("level") * F.col("weight"), F.col("cap")))
    return rows.select("source_key", "source_size", "weight", target.alias("target"))


def pack(sizes: DataFrame) -> DataFrame:
    """sizes with ``start``, the number of the source's words before the document.

    A source's documents are summed in hash buckets first and buckets after that, so no task holds a source.
    """
    buckets = max(1, -(-sizes.count() // BUCKET_ROWS))
    digits = F.substring(F.md5(F.col("doc_id").cast("string")), 1, 8)
    dealt = sizes.withColumn("bucket", F.coalesce(F.conv(digits, 16, 10).cast("long") % buckets, F.lit(0)))
    sums = dealt.groupBy("source_key", "bucket").agg(F.sum("size").alias("n"))
    before = Window.partitionBy("source_key").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    within = Window.partitionBy("source_key", "bucket").orderBy("doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    placed = dealt.withColumn("upto", F.sum("size").over(within)).join(sums, ["source_key", "bucket"])
    return placed.select("doc_id", "source_key", "size", (F.col("base") + F.col("upto") - F.col("size")).alias("start"))


def cut(placed: DataFrame, length: int) -> DataFrame:
    """doc_id, source_key, size, start, block, words: a row for each block that a document has words in."""
    end = F.col("start") + F.col("size")
    first, last = F.floor(F.col("start") / length), F.floor((end - 1) / length)
    rows = placed.where("size > 0").withColumn("block", F.explode(F.sequence(first, last)))
    return rows.withColumn("words", F.least(end, (F.col("block") + 1) * length) - F.greatest(F.col("start"), F.col("block") * length))


def permuted(x: Column, n: Column, keys: Column, tag: Column) -> Column:
    """Where a swap-or-not shuffle of 0..n-1 puts x: in each round (a key each) a number and its mirror change
    places or not. The rounds are one aggregate over the keys, so that no rule of the optimiser can multiply them."""
    rounds = F.transform(keys, lambda k, r: F.struct(k.alias("k"), r.alias("r")))

    def one(at: Column, key: Column) -> Column:
        partner = F.pmod(key["k"] + n - at, n)
        coin = F.substring(F.md5(F.concat_ws(":", tag, key["r"].cast("string"), F.greatest(at, partner).cast("string"))), 1, 1)
        return F.when(coin < "8", partner).otherwise(at)

    return F.coalesce(F.aggregate(rounds, x, one), F.lit(0).cast("long"))


def mix(
    docs: DataFrame,
    length: int = 64,
    shard_slots: int = 4096,
    weights: tuple[int, ...] = (1, 2, 3),
    most: int = 3,
    seed: int = 17,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
) -> Mix:
    """Plan a mix. Sources in order of code points, null last, get the weights in turn; see targets().

    Null texts have no words; documents without words are in no block; a source without words has target 0.
    Rows without an id and repeated rows take part as documents of their own. Documents of one source follow
    each other by bucket and id, so ties (repeated rows) change nothing. An empty table gives an empty mix. A
    source may have up to 2^31 blocks; take longer blocks beyond. Other columns are not read.
    """
    spark = docs.sparkSession
    sizes = written(word_sizes(docs, id_col, text_col, source_col), "mix-sizes")
    sources = written(targets(sizes, weights, most), "mix-sources")
    placed = pack(sizes)
    blocks = F.ceil(F.col("source_size") / length)
    wanted = sources.where("source_size > 0").withColumn("blocks", blocks).withColumn("want", F.col("target") * F.col("blocks") / F.col("source_size"))
    total = round(wanted.agg(F.sum("want")).first()[0] or 0)
    shards, rest = -(-total // shard_slots), total % shard_slots
    # Expected counts in a full shard and in the last one, their whole parts, and intervals of [0, 1) for the rest.
    everything, kind = Window.partitionBy(), Window.partitionBy("kind")
    order = kind.orderBy("source_key")
    slots_of = F.when(F.col("kind") == 0, F.lit(shard_slots)).otherwise(F.lit(rest or shard_slots))
    shares = (
        wanted.withColumn("share", F.col("want") / F.sum("want").over(everything))
        .withColumn("kind", F.explode(F.array(F.lit(0), F.lit(1))))
        .withColumn("expected", F.col("share") * slots_of)
        .withColumn("base", F.floor("expected"))
        .withColumn("part", F.col("expected") - F.col("base"))
        .withColumn("parts", F.greatest(F.sum("part").over(kind), F.lit(1e-300)))  # 0 where nothing is drawn
        .withColumn("drawn", slots_of - F.sum("base").over(kind))
        .withColumn("high", F.when(F.row_number().over(kind.orderBy(F.desc("source_key"))) == 1, 1.0).otherwise(F.sum("part").over(order) / F.col("parts")))
        .withColumn("low", (F.sum("part").over(order) - F.col("part")) / F.col("parts"))
    )
    shares = written(shares.select("kind", "source_key", "blocks", "base", "low", "high", "drawn"), "mix-shares")
    draws = {r["kind"]: r["drawn"] for r in shares.groupBy("kind").agg(F.first("drawn").alias("drawn")).collect()}  # two rows
    shard = spark.range(shards).select(F.col("id").alias("shard"), F.when(F.col("id") == shards - 1, 1).otherwise(0).alias("kind"))
    n = F.when(F.col("kind") == 1, F.lit(draws.get(1, 0))).otherwise(F.lit(draws.get(0, 0)))
    drawn = (
        shard.withColumn("draw", F.explode(F.when(n > 0, F.sequence(F.lit(0), n.cast("int") - 1)).otherwise(F.array().cast("array<int>"))))
        .withColumn("u", uniform(F.lit(seed), F.col("shard").cast("string"), F.col("draw").cast("string")))
        .withColumn("place", F.floor(F.col("u") * LOOKUP))
    )
    lookup = shares.where("high > low").withColumn("place", F.explode(F.sequence(F.floor(F.col("low") * LOOKUP), F.least(F.floor(F.col("high") * LOOKUP), F.lit(LOOKUP - 1)))))
    drawn = drawn.join(lookup.select("kind", "place", "source_key", "low", "high"), ["kind", "place"]).where("u >= low and u < high")
    drawn = written(drawn.select("shard", "source_key", "draw"), "mix-draws")
    wants = (
        shard.join(shares.where("base > 0").select("kind", "source_key", "base"), "kind")
        .select("shard", "source_key", F.col("base").alias("n"))
        .unionByName(drawn.select("shard", "source_key", F.lit(1).cast("long").alias("n")))
        .groupBy("shard", "source_key")
        .agg(F.sum("n").alias("n"))
        .withColumn("group", F.floor(F.col("shard") / SHARDS_A_SUM))
    )
    wants = written(wants, "mix-wants")
    # A source's slots are numbered through its shards, by sums of groups of shards and sums within a group; where its
    # cap is reached, its slots end, in the counts as in the slots.
    before = Window.partitionBy("source_key").orderBy("group").rowsBetween(Window.unboundedPreceding, -1)
    sums = wants.groupBy("source_key", "group").agg(F.sum("n").alias("all")).withColumn("base", F.coalesce(F.sum("all").over(before), F.lit(0))).drop("all")
    inside = Window.partitionBy("source_key", "group").orderBy("shard").rowsBetween(Window.unboundedPreceding, 0)
    numbered = wants.withColumn("upto", F.sum("n").over(inside)).join(sums, ["source_key", "group"]).join(small(shares.select("source_key", "blocks").distinct()), "source_key")
    numbered = numbered.withColumn("first", F.col("base") + F.col("upto") - F.col("n")).withColumn("n_slots", F.least("n", F.col("blocks") * most - F.col("first"))).where("n_slots > 0")
    counts = written(numbered.select("shard", "source_key", "n_slots", "first", "blocks"), "mix-counts")
    turn = F.explode(F.sequence(F.floor(F.col("first") / F.col("blocks")), F.floor((F.col("first") + F.col("n_slots") - 1) / F.col("blocks"))))
    parts = (
        counts.withColumn("pass", turn)
        .withColumn("from", F.greatest(F.col("first"), F.col("pass") * F.col("blocks")))
        .withColumn("upto", F.least(F.col("first") + F.col("n_slots"), (F.col("pass") + 1) * F.col("blocks")) - 1)
        .withColumn("tag", F.md5(F.concat_ws(":", F.lit(seed), F.col("source_key"), F.col("pass").cast("string"))))
    )
    keys = F.array(*[F.conv(F.substring(F.md5(F.concat_ws(":", F.col("tag"), F.lit(r))), 1, 13), 16, 10).cast("long") % F.col("blocks") for r in range(ROUNDS)])
    parts = parts.withColumn("keys", keys).repartition(max(1, -(-total // SLOTS_A_TASK)), "source_key", "shard", "pass")
    slots = parts.withColumn("rank", F.explode(F.sequence("from", "upto")))
    block = permuted(F.col("rank") - F.col("pass") * F.col("blocks"), F.col("blocks"), F.col("keys"), F.col("tag"))
    slots = slots.select("shard", "source_key", "rank", block.alias("block"))
    return Mix(sizes, sources, cut(placed, length), slots, counts.select("shard", "source_key", "n_slots"), length)


def taken(docs: DataFrame, **options) -> DataFrame:
    """doc_id, size, source_size, target, taken: how many words of each document the mix takes, repeats counted."""
    m = mix(docs, **options)
    copies = m.slots.groupBy("source_key", "block").agg(F.count(F.lit(1)).alias("copies"))
    used = (
        # The optimiser takes exploded slots for as small as the table they come from, and would broadcast them.
        m.pieces.join(copies.hint("merge"), ["source_key", "block"], "left")
        .groupBy("doc_id", "source_key", "size", "start")
        .agg(F.sum(F.col("words") * F.coalesce("copies", F.lit(0))).alias("taken"))
        .select("doc_id", "source_key", "size", "taken")
    )
    none = m.sizes.where("size = 0").select("doc_id", "source_key", "size", F.lit(0).cast("long").alias("taken"))
    of = small(m.sources.select("source_key", "source_size", F.round("target", 6).alias("target")))
    return used.unionByName(none).join(of, "source_key").select("doc_id", "size", "source_size", "target", "taken")


def block_texts(docs: DataFrame, m: Mix, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """source_key, block, text: the words of each block, in order, joined by one space. Ids must be unique."""
    words = F.filter(F.split(F.coalesce(F.col(text_col), F.lit("")), r"[\x20\x09-\x0D]+"), lambda w: w != "")
    texts = docs.select(F.col(id_col).alias("doc_id"), words.alias("all_words"))
    first = F.greatest(F.lit(0), F.col("block") * m.length - F.col("start")) + 1
    part = F.array_join(F.slice("all_words", first.cast("int"), F.col("words").cast("int")), " ")
    rows = m.pieces.join(texts, "doc_id").select("source_key", "block", "start", part.alias("part"))
    parts = rows.groupBy("source_key", "block").agg(F.sort_array(F.collect_list(F.struct("start", "part"))).alias("parts"))
    return parts.select("source_key", "block", F.array_join(F.transform("parts", lambda p: p["part"]), " ").alias("text"))


def mixed_texts(docs: DataFrame, **options) -> DataFrame:
    """shard, source_key, rank, block, text: the output itself, a block of text for each slot. Its shards have the
    slots of each source that Mix.shard_counts says."""
    m = mix(docs, **options)
    return m.slots.hint("merge").join(block_texts(docs, m), ["source_key", "block"])


def mixed_documents(docs: DataFrame, seed: int = 17, id_col: str = "doc_id", **options) -> DataFrame:
    """Rows of docs, with all their columns, as often as the mix takes their words: the share taken / size is rounded up
    or down by a draw, so sources keep their totals. Rows without words are in no mix. Rows that share an id share
    their count."""
    t = taken(docs, seed=seed, id_col=id_col, **options).groupBy("doc_id").agg(F.sum("taken").alias("taken"), F.sum("size").alias("size"))
    share = F.col("taken") / F.greatest("size", F.lit(1))
    copies = F.floor(share + uniform(F.lit(seed), F.lit("copies"), F.col("doc_id").cast("string"))).cast("int")
    chosen_id, times, copy = (unused(x, docs) for x in ("id", "times", "copy"))
    chosen = written(t.select(F.col("doc_id").alias(chosen_id), copies.alias(times)).where(F.col(times) > 0), "mix-copies")
    rows = docs.join(small(chosen), docs[id_col].eqNullSafe(F.col(chosen_id)))
    return rows.withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(times)))).drop(chosen_id, times, copy)
