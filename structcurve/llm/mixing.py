"""Mixing sources to target weights, in DataFrame operations only.

Each source's words are packed into blocks of fixed length; each output shard draws how many of its
slots go to each source from the multinomial law of the targets; a source's slots run through pseudorandom permutations of its block indexes;
and slots and blocks meet in a join by index.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import text_of, written

#: Words are runs of characters other than these white spaces (a fixed pattern).
WORDS = r"[^\x20\x09-\x0D]+"
_M = 1 << 31
ROUNDS = 12
#: Cells of the unit interval by which a draw finds its source.
CELLS = 4096


def dice(x: Column, salt: Column | int = 0) -> Column:
    """A number below 2^31 from integers, the same in every engine: two steps of a linear congruence."""
    salted = salt if isinstance(salt, Column) else F.lit(salt)
    one = F.pmod(F.pmod(x, F.lit(_M)) * F.lit(1103515245) + salted * F.lit(12345) + F.lit(12345), F.lit(_M))
    mixed = one.bitwiseXOR(F.shiftright(one, 16))
    return F.pmod(mixed * F.lit(1103515245) + F.lit(12345), F.lit(_M))


def permuted(index: Column, n: Column, salt: Column) -> Column:
    """A pseudorandom permutation of 0..n-1 (swap-or-not rounds), n at most 2^30.

    In each round an index may swap with its mirror under a secret sum; both see the same coin, that of the larger.
    """

    def step(x: Column, r: Column) -> Column:
        mirror = F.pmod(F.pmod(dice(salt * F.lit(ROUNDS) + r, 7), n) - x, n)
        coin = F.shiftright(dice(F.greatest(x, mirror) * F.lit(ROUNDS) + r, salt), 20).bitwiseAND(F.lit(1).cast("bigint"))
        return F.when(coin == 1, mirror).otherwise(x)

    return F.aggregate(F.sequence(F.lit(0).cast("bigint"), F.lit(ROUNDS - 1).cast("bigint")), index.cast("bigint"), step)


def source_targets(sizes: DataFrame, share: float = 1.5, cap: float = 2.0, weights: tuple[float, ...] = (3, 1, 2)) -> DataFrame:
    """Adds ``rank, weight, target`` to ``(source, source_size)``.

    Sources in code point order, null last, take the weights in turn and split ``share`` of all words; a
    target stops at ``cap`` times its source and the excess goes to the others by weight until none is
    above.  That fixed point is one water level: sorted by cap over weight, a source is full if the level
    that the sources from it on could share reaches it.  One row per source: the window is small.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    fill = Window.orderBy("_ratio", "rank")
    table = F.array(*(F.lit(float(w)) for w in weights))
    ranked = sizes.withColumn("rank", F.row_number().over(order)).withColumn("weight", F.get(table, F.pmod(F.col("rank") - 1, F.lit(len(weights)))))
    ranked = ranked.withColumn("_cap", F.col("source_size") * F.lit(float(cap))).withColumn("_ratio", F.col("_cap") / F.col("weight"))
    everything = Window.partitionBy()
    ranked = ranked.withColumn("_total", F.sum("source_size").over(everything) * F.lit(float(share)))
    before = F.coalesce(F.sum("_cap").over(fill.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    left = F.sum("weight").over(fill.rowsBetween(0, Window.unboundedFollowing))
    level = (F.col("_total") - before) / left
    ranked = ranked.withColumn("_level", F.when(level < F.col("_ratio"), level))
    # the first source that is not full sets the level of all that are not
    open_level = F.min(F.when(F.col("_level").isNotNull(), F.struct("_ratio", "rank", "_level"))).over(everything)
    ranked = ranked.withColumn("_open", open_level["_level"])
    target = F.when(F.col("_open").isNull(), F.col("_cap")).otherwise(F.least("_cap", F.col("_open") * F.col("weight")))
    return ranked.withColumn("target", target).select("source", "source_size", "rank", "weight", "target")


def measured(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """``doc_id, source, size``: the only pass over the texts."""
    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(source_col).cast("string").alias("source"), F.regexp_count(text_of(text_col), F.lit(WORDS)).cast("bigint").alias("size"))


def packed(sizes: DataFrame, rows: int) -> DataFrame:
    """Adds ``start``: the first word's place in the stream of the document's source.

    Streams go through about sqrt(rows) parts by a hash of the id; the running sum is taken inside a part
    and over the parts' totals, so no task sees more than about sqrt(rows) rows of one source.
    """
    parts = max(1, math.isqrt(rows))
    dealt = sizes.withColumn("part", F.pmod(F.shiftright(dice(F.coalesce("doc_id", F.lit(0))), 6), F.lit(parts)))
    totals = dealt.groupBy("source", "part").agg(F.sum("size").alias("_n"))
    offsets = totals.select("source", "part", (F.sum("_n").over(Window.partitionBy("source").orderBy("part")) - F.col("_n")).alias("_offset"))
    inside = Window.partitionBy("source", "part").orderBy("doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    running = dealt.withColumn("_inside", F.sum("size").over(inside) - F.col("size"))
    o = offsets.withColumnsRenamed({"source": "_source", "part": "_part"})
    return running.join(o, F.col("source").eqNullSafe(F.col("_source")) & (F.col("part") == F.col("_part"))).select("doc_id", "source", "size", (F.col("_offset") + F.col("_inside")).alias("start"))


def drawn_slots(targets: DataFrame, block_words: int, slots: int, shard_slots: int) -> DataFrame:
    """``rank, shard, n, epoch, block``: one row per slot of the mix.

    Each slot of a shard draws its source with the probability of the source's share, so a shard's counts
    are multinomial.  Over all shards a source's count then misses its quota, the target in blocks, by
    a random amount, large for small sources.  The correction: of a source drawn too often, evenly spread
    slots are given up, and these go in order to the sources drawn too rarely.  Totals are then the quotas, which
    are the targets rounded to whole blocks.  A source's n-th slot is epoch n div blocks.
    """
    spark = targets.sparkSession
    blocks = F.ceil(F.col("source_size") / F.lit(block_words))
    upto = Window.orderBy("rank")
    t = targets.where("source_size > 0").withColumn("blocks", blocks).withColumn("_want", F.col("target") * F.col("blocks") / F.col("source_size"))
    t = t.withColumn("_sum", F.sum("_want").over(upto)).withColumn("_end", F.round("_sum").cast("bigint"))
    t = t.withColumn("quota", F.col("_end") - F.coalesce(F.lag("_end").over(upto), F.lit(0)))
    t = t.withColumn("_hi", F.col("_sum") / F.sum("_want").over(Window.partitionBy())).withColumn("_lo", F.coalesce(F.lag("_hi").over(upto), F.lit(0.0)))
    t = t.withColumn("_hi", F.when(F.lead("rank").over(upto).isNull(), F.lit(1.0)).otherwise(F.col("_hi")))
    cells = t.select("rank", "_lo", "_hi", F.explode(F.sequence(F.floor(F.col("_lo") * CELLS), F.least(F.floor(F.col("_hi") * CELLS), F.lit(CELLS - 1)))).alias("_cell"))
    each = F.lit(shard_slots).cast("bigint")
    s = spark.range(slots).select(F.floor(F.col("id") / each).alias("shard"), F.pmod("id", each).alias("_x"))
    s = s.withColumn("_u", (dice(dice(F.col("_x"), dice(F.col("shard"), 3)), 5) + F.lit(0.5)) / F.lit(float(_M))).withColumn("_cell", F.floor(F.col("_u") * CELLS))
    # a cell of the unit interval meets the few sources whose shares reach into it
    counts = written(s.join(cells, "_cell").where("_u >= _lo and _u < _hi").groupBy("rank", "shard").agg(F.count("*").alias("count")), "mix-counts")
    drawn = counts.groupBy("rank").agg(F.sum("count").alias("_drawn"))
    src = t.select("rank", "blocks", "quota").join(drawn, "rank", "left").withColumn("_drawn", F.coalesce("_drawn", F.lit(0)))
    src = src.withColumn("_over", F.greatest(F.col("_drawn") - F.col("quota"), F.lit(0))).withColumn("_under", F.greatest(F.col("quota") - F.col("_drawn"), F.lit(0)))
    src = written(src.withColumns({c: F.sum(n).over(upto) - F.col(n) for c, n in (("_given", "_over"), ("_taken", "_under"))}), "mix-draw")
    ends = F.sum("count").over(Window.partitionBy("rank").orderBy("shard"))
    # the table of counts is small and would be one task's; its slots are many
    ranked = counts.withColumn("_first", ends - F.col("count")).repartition(min(10_000, max(8, slots // 50_000)), "rank", "shard").join(src, "rank")
    slot = ranked.withColumn("_n", F.explode(F.sequence(F.col("_first"), F.col("_first") + F.col("count") - 1)))
    given = lambda n: F.floor((n + F.lit(0.5)) * (F.col("_over") / F.col("_drawn")))  # noqa: E731  (how many of the first n are given up)
    slot = slot.withColumn("_before", given(F.col("_n"))).withColumn("_free", given(F.col("_n") + 1) > F.col("_before"))
    kept = slot.where("not _free").select("rank", "shard", "blocks", (F.col("_n") - F.col("_before")).alias("n"))
    free = slot.where("_free").select("shard", (F.col("_given") + F.col("_before")).alias("_j"))
    short = src.where("_under > 0").select("rank", "blocks", "_drawn", "_taken", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("_under") - 1)).alias("_k"))
    short = short.select("rank", "blocks", (F.col("_taken") + F.col("_k")).alias("_j"), (F.col("_drawn") + F.col("_k")).alias("n"))
    slot = kept.union(free.join(short, "_j").select("rank", "shard", "blocks", "n"))
    slot = slot.withColumn("epoch", F.floor(F.col("n") / F.col("blocks")))
    return slot.select("rank", "shard", "n", "epoch", permuted(F.pmod("n", F.col("blocks")), F.col("blocks"), F.col("rank") * 16 + F.col("epoch")).alias("block"))


def mixture(docs: DataFrame, share: float = 1.5, cap: float = 2.0, weights: tuple[float, ...] = (3, 1, 2), block_words: int = 128, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> tuple[DataFrame, DataFrame, DataFrame]:
    """(documents, targets, pieces of the mix).

    documents: ``doc_id, source, size, start``; targets: see :func:`source_targets`; pieces: ``rank,
    shard, n, block, doc_id, start, word_from, word_to`` - which words of which document fill each slot.
    """
    sizes = written(measured(docs, id_col, text_col, source_col), "mix-sizes")
    by_source = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("_rows"))
    totals = by_source.agg(F.coalesce(F.sum("source_size"), F.lit(0)).alias("words"), F.coalesce(F.sum("_rows"), F.lit(0)).alias("rows")).first()
    block = max(block_words, -(-totals.words // (1 << 30)))
    targets = written(source_targets(by_source.drop("_rows"), share, cap, weights), "mix-targets")
    wanted = targets.where("source_size > 0").agg(F.sum(F.col("target") * F.ceil(F.col("source_size") / F.lit(block)) / F.col("source_size")).alias("n")).first().n
    slots = int(round(wanted or 0))
    placed = packed(sizes, totals.rows)
    placed = written(placed, "mix-placed")
    shard_slots = max(1024, math.isqrt(slots) if slots else 1)
    drawn = drawn_slots(targets, block, slots, shard_slots).where(F.col("epoch") < F.lit(math.floor(cap)))
    ranks = targets.select(F.col("source").alias("_source"), "rank")
    long = placed.where("size > 0").join(ranks, F.col("source").eqNullSafe(F.col("_source")))
    b = F.lit(block).cast("bigint")
    pieces = long.select("rank", "doc_id", "size", "start", F.explode(F.sequence(F.floor(F.col("start") / b), F.floor((F.col("start") + F.col("size") - 1) / b))).alias("block"))
    pieces = pieces.withColumn("word_from", F.greatest(F.col("block") * b - F.col("start"), F.lit(0))).withColumn("word_to", F.least((F.col("block") + 1) * b - F.col("start"), F.col("size")))
    return placed, targets, drawn.join(pieces, ["rank", "block"]).select("rank", "shard", "n", "block", "doc_id", "start", "size", "word_from", "word_to")


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """One row per document: ``doc_id, size, source_size, target, taken`` and ``source``.

    Null and empty texts have size 0 and are never taken; a null source is a source, the last one; null
    ids and repeated rows are rows of their own; an empty table gives an empty table; equal runs agree,
    as the draw rests on ids, sizes and sources only.  No task holds a whole source: streams are
    dealt in about sqrt(rows) parts and blocks are joined by (source, block).
    """
    placed, targets, pieces = mixture(docs, **options)
    taken = pieces.groupBy("rank", "start", "doc_id").agg(F.sum(F.col("word_to") - F.col("word_from")).alias("taken"))
    t = targets.select(F.col("source").alias("_source"), "rank", "source_size", "target")
    rows = placed.join(t, F.col("source").eqNullSafe(F.col("_source")), "left")
    k = taken.select(F.col("rank").alias("_rank"), F.col("start").alias("_start"), F.col("doc_id").alias("_id"), F.col("taken").alias("_taken"))
    joined = rows.join(k, (F.col("rank") == F.col("_rank")) & (F.col("start") == F.col("_start")) & F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("size") > 0), "left")
    return joined.select("doc_id", "size", "source_size", "target", F.coalesce("_taken", F.lit(0)).cast("bigint").alias("taken"), "source")
