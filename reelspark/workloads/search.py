"""Queries whose result is a compilation: spoken words, passages, telemetry, heat, hue, samples."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reelspark.engine import exec as engine
from reelspark.functions.scalar import STAMP_SQL, fmt_timestamp
from reelspark.lift import relational
from reelspark.operators.joins import BROADCAST_ROWS, asof_join
from reelspark.operators.running import numbered, running
from reelspark.registry import query
from reelspark.session import table
from reelspark.sources import derive, gopindex
from reelspark.sources.derive import GOP_LEN
from reelspark.workloads.clips import SEG, frames_sql, task_gops, task_sources

WORD, AROUND = "enver", 38

_CAPS = "caps AS (SELECT 'cap/' || source AS source_id, doc_id, text, (n_chars + 14) // 15 AS n_frames, CAST(sum((n_chars + 14) // 15) OVER (PARTITION BY source ORDER BY doc_id) - (n_chars + 14) // 15 AS BIGINT) AS start_frame, CAST(sum((n_chars + 14) // 15) OVER (PARTITION BY source) AS BIGINT) AS total FROM documents)"


#: Every place of a word, overlapping ones too: the next one is looked for from the character behind the last one's first.
_PLACES = "o AS (SELECT source_id, doc_id, text, start_frame, total, CAST(instr(text, '{word}') AS BIGINT) AS pos FROM (SELECT * REPLACE (lower(text) AS text) FROM caps) WHERE contains(text, '{word}') UNION ALL SELECT source_id, doc_id, text, start_frame, total, CAST(pos + instr(substr(text, pos + 1), '{word}') AS BIGINT) FROM o WHERE contains(substr(text, pos + 1), '{word}'))"


def hits(spark: SparkSession, sf_dir: str, word: str) -> DataFrame:
    """Clips around every place of a word in every caption: (occ, source_id, doc_id, first, n, stamp_text).

    Occurrences are numbered by source and time (places of one frame share all other columns): sums per source, and a count in
    blocks of frames inside it. Only places are moved, never a text.
    """
    totals = derive.captions(spark, sf_dir).groupBy("source_id").agg(F.sum("n_frames").alias("total"))
    words = spark.createDataFrame([(0, word)], "item_id bigint, text string")
    found = in_captions(spark, sf_dir, words, F.lower("text")).join(F.broadcast(totals) if totals.count() <= BROADCAST_ROWS else totals, "source_id")
    frame = F.col("start_frame") + F.expr("at div 15")
    lo, hi = F.greatest(F.lit(0), frame - AROUND), F.least(F.col("total") - 1, frame + AROUND)
    rows = found.select("source_id", "doc_id", frame.alias("frame"), lo.alias("first"), (hi - lo + 1).alias("n"))
    before = rows.groupBy("source_id").agg(F.count("*").alias("c")).select(F.col("source_id").alias("s"), (F.sum("c").over(Window.orderBy("source_id")) - F.col("c")).alias("before"))
    stamp = fmt_timestamp(F.expr("frame * 1000 div 24"))
    return numbered(rows, ["source_id"], "frame", "r", then=["doc_id"]).join(before, F.col("source_id") == F.col("s")).select((F.col("before") + F.col("r") + 1).alias("occ"), "source_id", "doc_id", "first", "n", stamp.alias("stamp_text"))


@query("w_search", f"WITH RECURSIVE {_CAPS}, {_PLACES.format(word=WORD)}, h AS (SELECT *, start_frame + (pos - 1) // 15 AS frame FROM o) SELECT row_number() OVER (ORDER BY source_id, frame, doc_id) AS occ, source_id, doc_id, CAST(greatest(0, frame - 38) AS BIGINT) AS first, CAST(least(total - 1, frame + 38) - greatest(0, frame - 38) + 1 AS BIGINT) AS n, {STAMP_SQL.format('(frame * 1000 // 24)')} AS stamp_text FROM h")
def w_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every place of the word in every whole text."""
    return hits(spark, sf_dir, WORD)


@query("w_search_merged", f"WITH RECURSIVE {_CAPS}, {_PLACES.format(word=WORD)}, h AS (SELECT source_id, greatest(0, start_frame + (pos - 1) // 15 - 38) AS a, least(total - 1, start_frame + (pos - 1) // 15 + 38) AS b FROM o), g AS (SELECT *, max(b) OVER (PARTITION BY source_id ORDER BY a, b ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS m FROM h), i AS (SELECT *, sum(CASE WHEN m IS NULL OR a > m + 1 THEN 1 ELSE 0 END) OVER (PARTITION BY source_id ORDER BY a, b ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT source_id, CAST(min(a) AS BIGINT) AS first, CAST(max(b) AS BIGINT) AS last, count(*) AS places FROM i GROUP BY source_id, k")
def w_search_merged(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The compilation without repeats: clips of one source that overlap or touch are one. A place begins a clip if the place before it is
    more than a clip's length away, so runs are counted like any running sum."""
    h = hits(spark, sf_dir, WORD).select("source_id", "first", (F.col("first") + F.col("n") - 1).alias("last"), "occ")
    b = h.withColumn("b", F.floor(F.col("occ") / F.lit(4096)))
    # clips in order of their number are in order of both ends (equal lengths but at the clip's borders), so the one before is enough
    ends = b.groupBy("source_id", "b").agg(F.max(F.struct("occ", "last")).alias("end"))
    carry = ends.select(F.col("source_id").alias("s"), F.col("b").alias("c"), F.lag("end").over(Window.partitionBy("source_id").orderBy("b"))["last"].alias("carried"))
    seen = F.lag("last").over(Window.partitionBy("source_id", "b").orderBy("occ"))
    new = b.withColumn("seen", seen).join(carry, (F.col("source_id") == F.col("s")) & (F.col("b") == F.col("c"))).withColumn("prev", F.coalesce("seen", "carried"))
    new = new.withColumn("begins", F.when(F.col("prev").isNull() | (F.col("first") > F.col("prev") + 1), F.lit(1)).otherwise(F.lit(0)).cast("bigint")).select("source_id", "first", "last", "occ", "begins")
    runs = running(new, ["source_id"], "occ", "begins", "had").withColumn("k", F.col("had") + F.col("begins"))
    return runs.groupBy("source_id", "k").agg(F.min("first").alias("first"), F.max("last").alias("last"), F.count("*").alias("places")).drop("k")


@query("w_search_spec")
def w_search_spec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The compilation itself, over every place of the word: each clip's frames in order, labelled with number, source and time; frames come
    from the main clip at the caption's position (captioned clips have an index only). Returns digests of what is rendered."""
    n = table(spark, sf_dir, "orders").count()
    rows = running(hits(spark, sf_dir, WORD), [], "occ", "n", "start").select("*", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("n") - 1)).alias("k"))
    frames = rows.select((F.col("start") + F.col("k")).alias("gen"), F.lit("main").alias("source_id"), F.pmod(F.col("first") + F.col("k"), F.lit(n)).alias("idx"))
    dets = rows.select((F.col("start") + F.col("k")).alias("frame"), F.lit(1).alias("ord"), F.lit(0).alias("x1"), F.lit(0).alias("y1"), F.lit(15).alias("x2"), F.lit(6).alias("y2"), F.lit("N").alias("cls"), F.concat(F.lit("#"), F.col("occ").cast("string"), F.lit(" "), F.substring("source_id", 5, 20), F.lit(" "), "stamp_text").alias("text"))
    spec = relational.annotate(frames, dets, "label", "search", SEG, needed=True)
    return engine.digests(engine.render(spec, task_gops(spark, sf_dir, "label"), task_sources(spark, sf_dir), GOP_LEN)).select("gen", "md5")


@query("w_passage", f"WITH RECURSIVE {_CAPS}, o AS (SELECT item_id, source_id, doc_id, start_frame, caps.text AS text, b.text AS passage, CAST(instr(caps.text, b.text) AS BIGINT) AS pos FROM caps JOIN benchmark b ON contains(caps.text, b.text) UNION ALL SELECT item_id, source_id, doc_id, start_frame, text, passage, CAST(pos + instr(substr(text, pos + 1), passage) AS BIGINT) FROM o WHERE contains(substr(text, pos + 1), passage)) SELECT item_id, source_id, doc_id, CAST(start_frame + (pos - 1) // 15 AS BIGINT) AS frame FROM o")
def w_passage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every place of every passage in every whole text, by one linear multi-pattern scan of the texts."""
    found = in_captions(spark, sf_dir, table(spark, sf_dir, "benchmark"), F.col("text"))
    return found.select("item_id", "source_id", "doc_id", (F.col("start_frame") + F.expr("at div 15")).alias("frame"))


def in_captions(spark: SparkSession, sf_dir: str, passages: DataFrame, text: Column) -> DataFrame:
    """(source_id, doc_id, item_id, at, start_frame): texts are scanned where they are read, only places are moved."""
    texts = table(spark, sf_dir, "documents").select(F.concat(F.lit("cap/"), "source").alias("source_id"), "doc_id", text.alias("text"))
    starts = derive.captions(spark, sf_dir).select(F.col("source_id").alias("s"), F.col("doc_id").alias("d"), "start_frame")
    return containing(texts, passages).join(starts, F.col("source_id").eqNullSafe(F.col("s")) & F.col("doc_id").eqNullSafe(F.col("d"))).drop("s", "d")


PASSAGES = 20_000  # per automaton, which bounds what a task holds
PLACES = 50_000  # found places that a task holds before it passes them on


def containing(texts: DataFrame, passages: DataFrame, apart: bool = False) -> DataFrame:
    """texts' columns but text, item_id, at: the places (characters from 0) of every passage in every text that holds it.

    Overlapping places count, unless they are to be ``apart`` (each begins behind the last one's end). Passages go to workers in parts
    of at most ``PASSAGES``, each an Aho-Corasick automaton; a text passes all parts in turn while it is in a task. What a part's
    closure holds is bounded, and so is what comes to the driver at once.
    """
    import pyarrow as pa

    schema = [f for f in texts.schema.fields if f.name != "text"]
    names = [f.name for f in schema]
    ddl = ", ".join([*(f"{f.name} {f.dataType.simpleString()}" for f in schema), "item_id bigint", "at bigint"])
    known = passages.where("text <> ''").select("item_id", "text")
    parts = max(1, -(-known.count() // PASSAGES))
    dealt, out = known.withColumn("part", F.pmod(F.xxhash64("item_id"), F.lit(parts))), None
    for part in range(parts):
        pairs = [(r["item_id"], r["text"]) for r in (dealt.where(F.col("part") == part) if parts > 1 else dealt).select("item_id", "text").collect()]

        def run(it, pairs=pairs):
            import ahocorasick

            items: dict[str, list[int]] = {}
            for i, p in pairs:
                items.setdefault(p, []).append(i)
            machine = ahocorasick.Automaton()
            for p in items:
                machine.add_word(p, p)
            if items:
                machine.make_automaton()
            for b in it:
                rows, ids, ats = [], [], []

                def found(b=b, rows=rows, ids=ids, ats=ats):
                    at_rows = pa.array(rows, pa.int64())  # the texts themselves are not taken along, which would be a copy a place
                    out = pa.RecordBatch.from_arrays([*(b.column(n).take(at_rows) for n in names), pa.array(ids, pa.int64()), pa.array(ats, pa.int64())], names=[*names, "item_id", "at"])
                    for held in (rows, ids, ats):
                        held.clear()
                    return out

                for k, text in enumerate(b.column("text")):
                    ends: dict[str, int] = {}
                    for end, p in machine.iter(text.as_py() or "") if items else ():
                        at = end + 1 - len(p)
                        if apart:
                            if at < ends.get(p, 0):
                                continue
                            ends[p] = end + 1
                        for i in items[p]:
                            rows.append(k)
                            ids.append(i)
                            ats.append(at)
                            if len(rows) >= PLACES:
                                yield found()
                yield found()

        one = texts.select(*names, "text").mapInArrow(run, ddl)
        out = one if out is None else out.unionByName(one)
    return out


def hue_key(r: Column, g: Column, b: Column) -> Column:
    """An integer hue in 0..359999 from channel sums."""
    mx, mn = F.greatest(r, g, b), F.least(r, g, b)
    part = lambda a, c: F.floor(F.lit(60000.0) * (a - c) / (mx - mn)).cast("bigint")
    key = F.when(mx == mn, F.lit(0).cast("bigint")).when(r == mx, part(g, b)).when(g == mx, 120000 + part(b, r)).otherwise(240000 + part(r, g))
    return F.when(key < 0, key + 360000).otherwise(key)


_HUE = """WITH q AS (SELECT vec_id, list_transform(embedding, lambda e: CAST(least(255, greatest(0, floor((CAST(e AS DOUBLE) + 1) * 128))) AS BIGINT)) AS a FROM embeddings),
p AS (SELECT vec_id, a[8 * y + x + 1] - 16 AS yy, a[63 - 4 * (4 * (y // 2) + x // 2) + 1] - 128 AS u, a[4 * (4 * (y // 2) + x // 2) + 2 + 1] - 128 AS v FROM q, range(8) tx(x), range(8) ty(y)),
s AS (SELECT vec_id, CAST(sum(least(255, greatest(0, (298 * yy + 409 * v + 128) >> 8))) AS BIGINT) AS r, CAST(sum(least(255, greatest(0, (298 * yy - 100 * u - 208 * v + 128) >> 8))) AS BIGINT) AS g, CAST(sum(least(255, greatest(0, (298 * yy + 516 * u + 128) >> 8))) AS BIGINT) AS b FROM p GROUP BY 1),
k AS (SELECT vec_id, greatest(r, g, b) AS mx, least(r, g, b) AS mn, r, g, b FROM s),
h AS (SELECT vec_id, CASE WHEN mx = mn THEN 0 WHEN r = mx THEN CAST(floor(60000.0::DOUBLE * (g - b) / (mx - mn)) AS BIGINT) WHEN g = mx THEN 120000 + CAST(floor(60000.0::DOUBLE * (b - r) / (mx - mn)) AS BIGINT) ELSE 240000 + CAST(floor(60000.0::DOUBLE * (r - g) / (mx - mn)) AS BIGINT) END AS k0 FROM k),
f AS (SELECT vec_id, CASE WHEN k0 < 0 THEN k0 + 360000 ELSE k0 END AS hue_key FROM h)
SELECT CAST(row_number() OVER (ORDER BY hue_key, vec_id) - 1 AS BIGINT) AS pos, vec_id, CAST(hue_key AS BIGINT) AS hue_key FROM f"""


def hue_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vec_id, hue_key) of the frames of the short clip, by column functions on the quantised vectors."""
    q = table(spark, sf_dir, "embeddings").select("vec_id", F.transform(derive.quantised(F.col("embedding")), lambda v: v.cast("bigint")).alias("a"))
    xy = F.sequence(F.lit(0), F.lit(63))
    at = lambda i: F.get("a", i.cast("int"))
    block = lambda k: 4 * F.floor(k / 16) + F.floor(F.pmod(k, F.lit(8)) / 2)
    clip = lambda v: F.least(F.lit(255), F.greatest(F.lit(0), F.shiftright(v, 8)))

    def channel(u: int, v: int):
        one = lambda k: clip(298 * (at(k) - 16) + u * (at(63 - 4 * block(k)) - 128) + v * (at(4 * block(k) + 2) - 128) + 128)
        return F.aggregate(F.transform(xy, one), F.lit(0).cast("bigint"), lambda s, x: s + x)

    sums = q.select("vec_id", channel(0, 409).alias("r"), channel(-100, -208).alias("g"), channel(516, 0).alias("b"))
    return sums.select("vec_id", hue_key(F.col("r"), F.col("g"), F.col("b")).alias("hue_key"))


def global_position(rows: DataFrame, key: str, tie: str, width: int) -> DataFrame:
    """``pos`` of each row in the order of (key, tie): rank inside a range of keys plus the sizes of the ranges before."""
    b = rows.withColumn("b", F.floor(F.col(key) / F.lit(width)))
    starts = b.groupBy("b").agg(F.count("*").alias("n")).select("b", (F.sum("n").over(Window.orderBy("b")) - F.col("n")).alias("start"))
    rank = F.row_number().over(Window.partitionBy("b").orderBy(key, tie)) - 1
    return b.withColumn("r", rank).join(starts, "b").withColumn("pos", (F.col("start") + F.col("r")).cast("bigint")).drop("b", "r", "start")


@query("w_hue", _HUE)
def w_hue(spark: SparkSession, sf_dir: str) -> DataFrame:
    return global_position(hue_keys(spark, sf_dir), "hue_key", "vec_id", 5000).select("pos", "vec_id", "hue_key")


query("sort_hue", _HUE)(w_hue)


@query("w_telemetry", "WITH f AS (SELECT o_orderkey AS frame, 1704067200000000 + o_orderkey * 1000000 // 24 AS at FROM orders), e AS (SELECT event_id, epoch_us(ts) AS t, value FROM events) SELECT f.frame, e.event_id, e.value FROM f ASOF LEFT JOIN e ON f.at >= e.t")
def w_telemetry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The latest reading at every frame of the main clip, laid over footage that starts with the first day."""
    f = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("frame"), (F.lit(1704067200000000) + F.expr("o_orderkey * 1000000 div 24")).alias("at"))
    e = table(spark, sf_dir, "events").select("event_id", F.expr("unix_micros(cast(ts as timestamp))").alias("t"), "value")
    return asof_join(f, e, "at", "t", ["event_id", "value"], 3_600_000_000).select("frame", "hit.event_id", "hit.value")


@query("w_heat", "SELECT CAST(floor((epoch_us(ts) - 1704067200000000) / 3600000000.0) AS BIGINT) AS bucket, user_id % 8 AS gx, CAST(floor(value) AS BIGINT) % 8 AS gy, count(*) AS n FROM events GROUP BY ALL")
def w_heat(spark: SparkSession, sf_dir: str) -> DataFrame:
    return derive.heat_counts(spark, sf_dir)


@query("w_heat_overlay")
def w_heat_overlay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly heat rasters, stored as a lossless clip, laid over the main clip; digests of the result."""
    from reelspark.model.expr import node, ref
    from reelspark.model.schemas import NODE

    rows = derive.heat_frames(spark, sf_dir)
    n = table(spark, sf_dir, "orders").count()
    spec = rows.select(F.lit("heat").alias("spec_id"), F.col("idx").alias("gen"), F.expr(f"idx div {SEG}").alias("seg"), F.array(ref("main", F.pmod(F.col("idx"), F.lit(n))), node("pixfmt", [0], (), "bgr24"), ref("heat", F.col("idx")), node("heat", [1, 2], [96]), node("pixfmt", [3], (), "yuv420p")).cast(f"array<{NODE}>").alias("nodes"))
    gops = gopindex.encode(derive.main_frames(spark, sf_dir)).unionByName(gopindex.encode(rows))
    sources = spark.createDataFrame([("main", 16, 16, "yuv420p"), ("heat", 8, 8, "gray8")], "source_id string, width int, height int, fmt string")
    return engine.digests(engine.gop_exchange(spec, gops, sources, GOP_LEN)).select("gen", "md5")


_LUMA = "(3 * f.i + 7 * (x % 16) + 11 * (y % 16) + f.p) % 256"


@query("w_sidebyside", f"WITH f AS ({frames_sql()}), g AS (SELECT i // 4 AS gen, f.*, 16 * ((i % 4) % 2) AS ox, 16 * ((i % 4) // 2) AS oy FROM f WHERE i < (SELECT count(*) // 4 * 4 FROM orders)) SELECT gen, CAST(sum((3 * i + 7 * x + 11 * y + p) % 256) AS BIGINT) AS luma, md5(string_agg(CAST((3 * i + 7 * x + 11 * y + p) % 256 AS VARCHAR), ',' ORDER BY oy + y, ox + x)) AS luma_md5 FROM g, range(16) tx(x), range(16) ty(y) GROUP BY gen")
def w_sidebyside(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four frames side by side in one: sums and digest of the luma plane."""
    import hashlib

    n = table(spark, sf_dir, "orders").count() // 4 * 4
    cells = table(spark, sf_dir, "orders").where(F.col("o_orderkey") < n).select(F.expr("o_orderkey div 4").alias("gen"), F.pmod("o_orderkey", F.lit(4)).alias("cell"), F.lit("main").alias("source_id"), F.col("o_orderkey").alias("idx"))
    spec = relational.grid_spec(cells, "grid", SEG)
    out = engine.render(spec, task_gops(spark, sf_dir, "box"), task_sources(spark, sf_dir), GOP_LEN, plan="segment_local")

    def luma(it):
        import pandas as pd

        for b in it:
            yield pd.DataFrame({"gen": b["gen"], "luma": [sum(d[:1024]) for d in b["data"]], "luma_md5": [hashlib.md5(",".join(map(str, d[:1024])).encode()).hexdigest() for d in b["data"]]})

    return out.select("gen", "data").mapInPandas(luma, "gen bigint, luma bigint, luma_md5 string")


def _reference_digests(spark: SparkSession, sf_dir: str, rows: DataFrame) -> DataFrame:
    spec = relational.sequence_spec(rows, "clip", SEG)
    return engine.digests(engine.render(spec, task_gops(spark, sf_dir, "box"), task_sources(spark, sf_dir), GOP_LEN)).select("gen", "md5")


def _base_md5(gen: str, where: str) -> str:
    yuv = "string_agg(CAST((3 * i + 7 * x + 11 * y + p) % 256 AS VARCHAR), ',' ORDER BY y, x)"
    u = "string_agg(CAST((c + 5 * x + 3 * y) % 256 AS VARCHAR), ',' ORDER BY y, x) FILTER (x < 8 AND y < 8)"
    v = "string_agg(CAST((40 * k + 2 * x + 9 * y) % 256 AS VARCHAR), ',' ORDER BY y, x) FILTER (x < 8 AND y < 8)"
    return f"WITH f AS ({frames_sql(where)}) SELECT {gen} AS gen, md5({yuv} || ',' || {u} || ',' || {v}) AS md5 FROM f, range(16) tx(x), range(16) ty(y) GROUP BY i"


@query("w_sample_1fps", _base_md5("i // 24", "o_orderkey % 24 = 0"))
def w_sample_1fps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One frame a second: the workload's own stride."""
    o = table(spark, sf_dir, "orders").where("o_orderkey % 24 = 0").select(F.expr("o_orderkey div 24").alias("gen"), F.lit("main").alias("source_id"), F.col("o_orderkey").alias("idx"))
    return _reference_digests(spark, sf_dir, o)


@query("w_keyframes", _base_md5("i // 60", "o_orderkey % 60 = 0"))
def w_keyframes(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders").where("o_orderkey % 60 = 0").select(F.expr("o_orderkey div 60").alias("gen"), F.lit("main").alias("source_id"), F.col("o_orderkey").alias("idx"))
    return _reference_digests(spark, sf_dir, o)


@query("w_reverse_render", _base_md5("(SELECT max(o_orderkey) FROM orders) - i", "TRUE"))
def w_reverse_render(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole clip backwards, with pixels."""
    last = table(spark, sf_dir, "orders").agg(F.max("o_orderkey").alias("m")).first()["m"]
    o = table(spark, sf_dir, "orders").select((F.lit(last) - F.col("o_orderkey")).alias("gen"), F.lit("main").alias("source_id"), F.col("o_orderkey").alias("idx"))
    return _reference_digests(spark, sf_dir, o)


@query("pack_masks", "SELECT vec_id AS mask_id, CAST(len(list_filter(embedding, lambda e: floor((CAST(e AS DOUBLE) + 1) * 128) >= 128)) AS BIGINT) AS n_set FROM embeddings")
def pack_masks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Masks as frames of a lossless one-channel clip: set pixels counted after encoding and decoding."""
    back = gopindex.decode(gopindex.encode(derive.mask_frames(spark, sf_dir), 30))
    ones = F.length(F.regexp_replace(F.hex("raw"), "00", "")) / 2
    return back.select(F.col("idx").alias("mask_id"), ones.cast("bigint").alias("n_set"))


@query("m_mask_bytes", "SELECT 'inline' AS kind, CAST(64 * (SELECT count(*) FROM lineitem) AS BIGINT) AS bytes")
def m_mask_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes that masks would take as constants, one copy per use (the packed clip's bytes depend on the compressor: see the test)."""
    return table(spark, sf_dir, "lineitem").agg(F.lit("inline").alias("kind"), (F.count("*") * 64).alias("bytes"))


_SHOW = r"""WITH u AS (SELECT conv_id, turn, lower(text) AS t FROM conversations WHERE role = 'user'),
i AS (SELECT conv_id, turn, CASE WHEN regexp_matches(t, '\b(telemetry|speed|sensor|readings?|overlay)\b') THEN 'telemetry overlay' WHEN regexp_matches(t, '\b(hue|colou?rs?|rainbow|sort(ed)?)\b') THEN 'hue order' WHEN regexp_matches(t, '\b(box(es)?|detect[a-z]*|objects?|class)\b') THEN 'boxes of class' ELSE 'search clip' END AS intent,
  CASE WHEN regexp_extract(t, '[''"]([a-z]{3,})[''"]', 1) <> '' THEN regexp_extract(t, '[''"]([a-z]{3,})[''"]', 1) WHEN regexp_extract(t, '\b(?:says?|said|mentions?|spoken)\s+([a-z]{3,})', 1) <> '' THEN regexp_extract(t, '\b(?:says?|said|mentions?|spoken)\s+([a-z]{3,})', 1) ELSE regexp_extract(t, '([a-z]{7,})', 1) END AS w FROM u),
j AS (SELECT conv_id, turn, intent, CASE WHEN intent = 'search clip' THEN w ELSE '' END AS word FROM i),
n AS (SELECT word, CAST(sum((length(lower(text)) - length(replace(lower(text), word, ''))) // length(word)) AS BIGINT) AS places FROM (SELECT DISTINCT word FROM j WHERE word <> ''), documents GROUP BY word)
SELECT conv_id, turn, intent, j.word, CASE intent WHEN 'search clip' THEN coalesce(n.places, 0) * 77 WHEN 'boxes of class' THEN (SELECT count(DISTINCT l_orderkey) FROM lineitem WHERE l_returnflag = 'A') WHEN 'hue order' THEN (SELECT count(*) FROM embeddings) ELSE (SELECT count(*) FROM orders) END AS spec_frames FROM j LEFT JOIN n ON n.word = j.word"""


@query("w_show_me", _SHOW)
def w_show_me(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each request's intent and the frames its query asks for (rules stand in for a model; clips here are unclipped: 77 frames a place)."""
    from reelspark.dialog.show_me import intents, sizes

    turns = table(spark, sf_dir, "conversations").where("role = 'user'").select("conv_id", "turn", "text")
    asked = intents(turns)
    known = asked.join(sizes(spark, sf_dir, asked), ["intent", "word"], "left")
    return known.select("conv_id", "turn", "intent", "word", F.coalesce("spec_frames", F.lit(0)).alias("spec_frames"))


def around(frame: Column, total: Column, k: int = AROUND) -> tuple[Column, Column]:
    return F.greatest(F.lit(0), frame - k), F.least(total - 1, frame + k)
