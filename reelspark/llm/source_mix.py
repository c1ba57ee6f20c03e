"""Mixing sources to target weights, with DataFrame functions only.

Each source's documents form one stream of words, in a pseudorandom order, packed into blocks of a fixed
length. The mix is a sequence of output shards of ``SHARD_SLOTS`` slots. Every slot draws its source by the weights, so a shard's
counts are a multinomial draw; the draws are then reconciled with the targets (``Mix._settle``): a source
drawn too often gives up a pseudorandom choice of its slots, and those go to the sources drawn too seldom. So a shard's counts carry the
noise of sampling (and a share of the few moved slots), while the totals are met. The k-th slot of a source (in
a pseudorandom order of its slots over all shards) takes, in its pass k div B over the source's B blocks, the block that a
permutation of that source and pass gives; slots and blocks are joined by (source, block).

Positions in a stream come from three levels of sums (bands of buckets of a source, buckets, rows of a bucket), so a
source that holds a third of all rows is many buckets and never one task; likewise slots (bands of shards, shards, slots of a shard). Rows that agree
in every key are counted first and then numbered, so that a third of all rows with one id (or none) spreads over the buckets like any others.
Shuffles carry no text.

Defined results: a null text has size 0; a null source is a source, the last; rows of size 0 are never taken; repeated rows are
rows of their own; an empty table gives an empty result; no row is taken more than ``MOST`` times its size.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reelspark.llm.common import WORD_SQL, Scratch, fresh

MOST, WEIGHTS, SEED = 3, (1, 2, 3), 20
BUCKET_ROWS, BUCKETS, SHARD_SLOTS, SHARDS, CHUNK, WALK = 128, 1_024, 1_024, 1_024, 8_192, 64
LONGEST_BLOCK, SHORTEST_BLOCK, BLOCKS_PER_SOURCE = 2_048, 16, 512


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_SQL)), F.lit(0)).cast("bigint")


def targets(sizes: DataFrame) -> DataFrame:
    """(source, source_size) -> also sid (rank by code point, null last), weight, target.

    Sources sorted by size over weight reach their limit first; with the limits of all before a source
    taken off, the rest is shared by the weights left, and the first that stays below its limit fixes
    the share of all after it. The windows run over one row per source.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    s = sizes.withColumn("sid", F.row_number().over(by_name).cast("bigint"))
    s = s.withColumn("weight", F.element_at(F.array(*map(F.lit, WEIGHTS)), (F.pmod(F.col("sid") - 1, F.lit(len(WEIGHTS))) + 1).cast("int")).cast("bigint"))
    order = [F.col("source_size") / F.col("weight"), F.col("sid")]
    after, before, all_rows = Window.orderBy(*order).rowsBetween(0, Window.unboundedFollowing), Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1), Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    limit = F.col("source_size") * MOST
    s = s.withColumns({"limit": limit, "left": F.sum("source_size").over(all_rows) - F.coalesce(F.sum(limit).over(before), F.lit(0)), "weights": F.sum("weight").over(after)})
    s = s.withColumn("rate", F.col("left") / F.col("weights"))
    s = s.withColumn("share", F.first(F.when(F.col("rate") * F.col("weight") <= F.col("limit"), F.col("rate")), ignorenulls=True).over(all_rows))
    capped = F.col("share").isNull() | (F.col("share") * F.col("weight") > F.col("limit"))
    return s.select("source", "source_size", "sid", "weight", F.when(capped, F.col("limit").cast("double")).otherwise(F.col("share") * F.col("weight")).alias("target"))


def block_words(total: int, sources: int) -> int:
    """Long blocks for large inputs; short enough that half a block is little against any source's share."""
    return max(SHORTEST_BLOCK, min(LONGEST_BLOCK, total // max(1, sources * BLOCKS_PER_SOURCE)))


def permuted(value: Column, size: Column, *key: Column) -> Column:
    """A keyed pseudorandom permutation of 0..size-1: Feistel rounds on a square of side ceil(sqrt(size)),
    walked until the value is inside again. Outside lie at most 2 * side values, so a walk of ``WALK`` steps is
    certain to end for small sizes and misses with a chance below 1e-70 for others; a miss raises an error."""
    side = F.greatest(F.ceil(F.sqrt(size.cast("double"))), F.lit(1)).cast("bigint")

    def once(v: Column) -> Column:
        x, y = F.floor(v / side).cast("bigint"), F.pmod(v, side)
        for r in range(4):
            x, y = y, F.pmod(x + F.pmod(F.xxhash64(F.lit(SEED + r), y, *key), side), side)
        return x * side + y

    walked = F.aggregate(F.sequence(F.lit(1), F.lit(WALK)), once(value), lambda v, _: F.when(v < size, v).otherwise(once(v)))
    return F.when(walked < size, walked).otherwise(F.raise_error(F.lit("permutation walk did not end")))


def draw(plan: DataFrame, n_slots: int, n_sources: int) -> DataFrame:
    """(shard, position, sid): every slot draws a source by the plan's shares (sid, first, n_slots).

    The draw is a number below 2 ** 53; each source owns an interval of them. Slots meet sources in the cells of a grid over the
    numbers, an equality join in which no cell is hot, however large a source's share."""
    spark, cells = plan.sparkSession, 1 << min(16, max(10, math.ceil(math.log2(4 * max(1, n_sources)))))
    edge = lambda c: F.floor(c.cast("double") / F.lit(float(n_slots)) * F.lit(float(1 << 53))).cast("bigint")
    width = F.lit((1 << 53) // cells)
    owned = plan.where("n_slots > 0").select("sid", edge(F.col("first")).alias("lo"), edge(F.col("first") + F.col("n_slots")).alias("hi"))
    owned = owned.withColumn("cell", F.explode(F.sequence(F.floor(F.col("lo") / width).cast("bigint"), F.floor((F.col("hi") - 1) / width).cast("bigint"))))
    number = F.shiftrightunsigned(F.xxhash64(F.lit(SEED + 9), "id"), 11)
    asked = spark.range(0, n_slots, 1, max(1, min(20_000, n_slots // (8 * CHUNK)))).select("id", number.alias("u")).withColumn("cell", F.floor(F.col("u") / width).cast("bigint"))
    return asked.join(owned, "cell").where("u >= lo AND u < hi").select(F.expr(f"id div {SHARD_SLOTS}").alias("shard"), F.pmod("id", F.lit(SHARD_SLOTS)).alias("position"), "sid")


def numbered(rows: DataFrame, keys: list[str], twin: str) -> DataFrame:
    """Equal rows told apart by a number from 0: counted first, so that many equal ones never meet in one task."""
    counted = rows.groupBy(*rows.columns).agg(F.count("*").alias("n_equal"))
    few = counted.where(F.col("n_equal") <= CHUNK).withColumn(twin, F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("n_equal") - 1)))
    many = counted.where(F.col("n_equal") > CHUNK).withColumn("part", F.explode(F.sequence(F.lit(0).cast("bigint"), F.expr(f"(n_equal - 1) div {CHUNK}"))))
    many = many.repartition(*keys, "part").withColumn(twin, F.explode(F.sequence(F.col("part") * CHUNK, F.least((F.col("part") + 1) * CHUNK, F.col("n_equal")) - 1)))
    return few.drop("n_equal").unionByName(many.drop("n_equal", "part"))


class Mix:
    """A mix over rows (source, size, order columns...): its plan, its slots, and where every row stands.

    ``rows`` must hold ``source`` and ``size``; ``keys`` name the columns that order and identify rows.
    """

    def __init__(self, rows: DataFrame, keys: list[str], words: int | None = None):
        self.keys, self.scratch = keys, Scratch(rows, "mix")
        sized = rows.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_rows"))
        facts = sized.agg(F.coalesce(F.sum("source_size"), F.lit(0)).alias("total"), F.count("*").alias("sources"), F.coalesce(F.max("n_rows"), F.lit(0)).alias("most")).first()
        self.words = words or block_words(facts["total"], facts["sources"])
        buckets = max(1, -(-facts["most"] // BUCKET_ROWS))
        blocks = F.ceil(F.col("source_size") / self.words).cast("bigint")
        # the slots of a source: its target over the mean length of its blocks (its last block may be short)
        n_slots = F.when(F.col("source_size") > 0, F.round(F.col("target") * blocks / F.col("source_size"))).otherwise(0).cast("bigint")
        plan = targets(sized.select("source", "source_size")).withColumns({"n_blocks": blocks, "n_slots": n_slots})
        whole = Window.orderBy("sid")
        self.plan = self.scratch.keep(plan.withColumn("first", F.sum("n_slots").over(whole) - F.col("n_slots")))
        n = self.plan.agg(F.coalesce(F.sum("n_slots"), F.lit(0))).first()[0]
        self.drawn = self.scratch.keep(draw(self.plan, n, facts["sources"]))
        self.slots = self.scratch.keep(self._settle())
        dealt = rows.withColumn("bucket", F.pmod(F.xxhash64(F.lit(SEED), *keys), F.lit(buckets)))
        sums = dealt.groupBy("source", "bucket").agg(F.sum("size").alias("words")).withColumn("band", F.expr(f"bucket div {BUCKETS}"))
        inside = Window.partitionBy("source", "band").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
        bands = sums.groupBy("source", "band").agg(F.sum("words").alias("words"))
        bands = bands.join(self.plan, bands["source"].eqNullSafe(self.plan["source"])).select(bands["source"].alias("b_source"), F.col("band").alias("b_band"), F.coalesce(F.sum("words").over(Window.partitionBy("sid").orderBy("band").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("first_word"), "sid", "source_size", "target")
        sums = sums.withColumn("inner", F.coalesce(F.sum("words").over(inside), F.lit(0)))
        named = sums.join(bands, (F.col("band") == F.col("b_band")) & F.col("source").eqNullSafe(F.col("b_source"))).select("b_source", F.col("bucket").alias("b_bucket"), (F.col("first_word") + F.col("inner")).alias("offset"), "sid", "source_size", "target")
        placed = dealt.join(named, (F.col("bucket") == F.col("b_bucket")) & F.col("source").eqNullSafe(F.col("b_source"))).drop("b_source", "b_bucket")
        order = Window.partitionBy("sid", "bucket").orderBy(F.xxhash64(F.lit(SEED + 1), *keys), *keys, "size")
        self.rows = placed.withColumns({"row": F.row_number().over(order), "start": F.col("offset") + F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0)) - F.col("size")})

    def _settle(self) -> DataFrame:
        """The draws reconciled with the plan, as slots: shard, position, sid, pass, block.

        A source's drawn slots are numbered over all shards and permuted: those numbered below its target stay its own; the others, numbered on
        over all sources, go to the sources with too few, unit by unit."""
        per = self.drawn.groupBy("shard", "sid").agg(F.count("*").alias("n")).withColumn("band", F.expr(f"shard div {SHARDS}"))
        bands = per.groupBy("sid", "band").agg(F.sum("n").alias("n"))
        before = lambda w: F.coalesce(F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        firsts = bands.select("sid", "band", before(Window.partitionBy("sid").orderBy("band")).alias("band_first"))
        whole = Window.orderBy("sid")
        drawn = bands.groupBy("sid").agg(F.sum("n").alias("drawn"))
        plan = self.plan.select("sid", "n_slots", "n_blocks").join(drawn, "sid", "left").withColumn("drawn", F.coalesce("drawn", F.lit(0)))
        plan = plan.withColumns({"over": F.greatest(F.col("drawn") - F.col("n_slots"), F.lit(0)), "under": F.greatest(F.col("n_slots") - F.col("drawn"), F.lit(0))})
        plan = self.scratch.keep(plan.withColumns({"over_first": F.sum("over").over(whole) - F.col("over"), "under_first": F.sum("under").over(whole) - F.col("under")}))
        per = per.withColumn("inner", before(Window.partitionBy("sid", "band").orderBy("shard"))).join(firsts, ["sid", "band"]).join(plan, "sid")
        rank = F.row_number().over(Window.partitionBy("shard", "sid").orderBy("position"))
        k = self.drawn.withColumn("rank", rank).join(per, ["shard", "sid"]).withColumn("k", permuted(F.col("band_first") + F.col("inner") + F.col("rank") - 1, F.col("drawn"), F.lit(1), F.col("sid")))
        own = k.where("k < n_slots").select("shard", "position", "sid", "k", "n_blocks")
        spare = k.where("k >= n_slots").select("shard", "position", (F.col("over_first") + F.col("k") - F.col("n_slots")).alias("unit"))
        asked = plan.where("under > 0").withColumn("unit", F.explode(F.sequence(F.col("under_first"), F.col("under_first") + F.col("under") - 1)))
        moved = spare.join(asked.select("unit", "sid", (F.col("drawn") + F.col("unit") - F.col("under_first")).alias("k"), "n_blocks"), "unit").select("shard", "position", "sid", "k", "n_blocks")
        slots = own.unionByName(moved).withColumn("pass", F.expr("k div n_blocks"))
        return slots.select("sid", "pass", permuted(F.pmod("k", "n_blocks"), F.col("n_blocks"), F.col("sid"), F.col("pass")).alias("block"), "shard", "position")

    def pieces(self) -> DataFrame:
        """One row per (row, block) that overlap: with the words of the row in the block; block null for empty rows."""
        last = F.expr(f"(start + size - 1) div {self.words}")
        blocks = F.when(F.col("size") > 0, F.sequence(F.expr(f"start div {self.words}"), last))
        out = self.rows.withColumn("block", F.explode_outer(blocks))
        lo, hi = F.greatest(F.col("start"), F.col("block") * self.words), F.least(F.col("start") + F.col("size"), (F.col("block") + 1) * self.words)
        return out.withColumns({"word_from": lo - F.col("start"), "n_piece": hi - lo})

    def layout(self) -> DataFrame:
        """The mix itself: for every slot (shard, position) the pieces of its block, in order."""
        return self.slots.join(self.pieces().where("block IS NOT NULL"), ["sid", "block"]).select("shard", "position", "sid", "pass", "block", *self.keys, "word_from", "n_piece", "start")

    def shard_counts(self, settled: bool = True) -> DataFrame:
        """Slots of each source in each shard: of the mix, or as first drawn."""
        return (self.slots if settled else self.drawn).groupBy("shard", "sid").count()

    def taken(self) -> DataFrame:
        """Every row with the words that the mix takes of it, repeats counted, the passes' blocks, and its first place in the mix."""
        uses = self.slots.groupBy("sid", "block").agg(F.count("*").alias("uses"), F.collect_list("pass").alias("passes"), F.min(F.struct("shard", "position")).alias("place"))
        joined = self.pieces().join(uses, ["sid", "block"], "left").withColumn("uses", F.coalesce("uses", F.lit(0)))
        chosen = F.collect_list(F.when(F.col("uses") > 0, F.struct("word_from", "n_piece", "passes")))
        carried = [F.first(c).alias(c) for c in ("source", "size", "source_size", "target", *self.keys)]
        return joined.groupBy("sid", "bucket", "row").agg(*carried, F.coalesce(F.sum(F.col("n_piece") * F.col("uses")), F.lit(0)).alias("taken"), chosen.alias("chosen"), F.min("place").alias("place"))


def digest(docs: DataFrame) -> DataFrame:
    """The columns that op3 returns; first_shard and first_position: where the row's words stand first in the mix."""
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("source").cast("string").alias("source"), word_count(F.col("text")).alias("size"), F.xxhash64("text").alias("ka"))
    rows = Scratch(docs, "mix").keep(numbered(rows, ["doc_id", "ka"], "twin"))
    return Mix(rows, ["doc_id", "ka", "twin"]).taken().select("doc_id", "size", "source_size", F.col("target").cast("double").alias("target"), "taken", F.col("place.shard").alias("first_shard"), F.col("place.position").alias("first_position"))


def mixed(docs: DataFrame) -> DataFrame:
    """The mix as documents (pipeline stage): per pass over a source, each row with the words taken in that pass.

    A row taken whole keeps its text as it is; of others the taken words are joined by spaces. A row taken in no pass
    is not part of the mix. The sums of words by source are those of ``digest``.
    """
    a, b, c, twin = fresh(docs, "m_text", "m_id", "m_null", "m_twin")
    keyed = docs.withColumns({a: F.xxhash64(F.coalesce("text", F.lit("")), F.coalesce(F.col("source").cast("string"), F.lit("")), F.col("source").isNull()), b: F.coalesce(F.col("doc_id").cast("bigint"), F.lit(-(1 << 63))), c: F.col("doc_id").isNull()})
    rows = keyed.select(F.col(a).alias("ka"), F.col(b).alias("kb"), F.col(c).alias("kc"), F.col("source").cast("string").alias("source"), word_count(F.col("text")).alias("size"))
    rows = Scratch(docs, "mix").keep(numbered(rows, ["ka", "kb"], "kt"))
    taken = Mix(rows, ["ka", "kb", "kc", "kt"]).taken().where("taken > 0")
    # rows that agree in all keys are told apart by a number on both sides
    ka, kb, kc, kt, size, chosen, p = fresh(docs, "m_ka", "m_kb", "m_kc", "m_kt", "m_size", "m_chosen", "m_pass")
    told = taken.select(F.col("ka").alias(ka), F.col("kb").alias(kb), F.col("kc").alias(kc), F.col("kt").alias(kt), F.col("size").alias(size), F.col("chosen").alias(chosen))
    rest = [x for x, kind in docs.dtypes if x not in ("doc_id", "text") and "map<" not in kind and "variant" not in kind]
    texts = keyed.withColumn(twin, F.row_number().over(Window.partitionBy(a, b, c).orderBy(F.xxhash64(*rest) if rest else F.lit(0))) - 1)
    same = (F.col(a) == F.col(ka)) & (F.col(b) == F.col(kb)) & (F.col(c) == F.col(kc)) & ((F.col(twin) - F.col(kt)) == 0)
    out = texts.join(told, same).withColumn(p, F.explode(F.array_distinct(F.flatten(F.transform(chosen, lambda x: x["passes"])))))
    mine = F.array_sort(F.transform(F.filter(chosen, lambda x: F.array_contains(x["passes"], F.col(p))), lambda x: F.struct(x["word_from"], x["n_piece"])))
    words = F.regexp_extract_all(F.col("text"), F.lit(WORD_SQL), F.lit(0))
    part = F.array_join(F.flatten(F.transform(mine, lambda x: F.slice(words, (x["word_from"] + 1).cast("int"), x["n_piece"].cast("int")))), " ")
    n = F.aggregate(mine, F.lit(0).cast("bigint"), lambda s, x: s + x["n_piece"])
    out = out.withColumn("text", F.when(n >= F.col(size), F.col("text")).otherwise(part))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(dict(docs.dtypes)["n_chars"]))
    return out.select(*docs.columns)
