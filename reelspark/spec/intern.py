"""Interning: equal sub-expressions of a spec are stored once, and the inverse."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reelspark.model.schemas import NODE


def node_hashes(nodes: Column) -> Column:
    """Content hash of every node's sub-tree, bottom-up within the row."""
    def add(acc: Column, n: Column) -> Column:
        kids = F.array_join(F.transform(n["kids"], lambda k: F.get(acc, k)), ",")
        return F.concat(acc, F.array(F.sha2(F.concat_ws("|", n["op"], kids, F.array_join(n["ints"], ","), n["text"]), 256)))

    return F.aggregate(nodes, F.array().cast("array<string>"), add)


def intern(spec: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(spec_nodes, spec_roots). One shuffle on (spec, hash), with the distinct done per map task first."""
    hashed = spec.withColumn("hashes", node_hashes(F.col("nodes")))
    each = hashed.select("spec_id", F.explode(F.arrays_zip("hashes", "nodes")).alias("z"), "hashes")
    nodes = each.select("spec_id", F.col("z.hashes").alias("node_id"), F.col("z.nodes.op").alias("op"), F.transform("z.nodes.kids", lambda k: F.get("hashes", k)).alias("kids"), F.col("z.nodes.ints").alias("ints"), F.col("z.nodes.text").alias("text"))
    nodes = nodes.groupBy("spec_id", "node_id").agg(F.first("op").alias("op"), F.first("kids").alias("kids"), F.first("ints").alias("ints"), F.first("text").alias("text"))
    return nodes, hashed.select("spec_id", "gen", "seg", F.element_at("hashes", -1).alias("root_id"), "hashes")


def expand(nodes: DataFrame, roots: DataFrame) -> DataFrame:
    """Back to one post-order array per generation; positions come from the stored order of hashes."""
    wanted = roots.select("spec_id", "gen", "seg", F.posexplode("hashes").alias("pos", "node_id"))
    joined = wanted.join(nodes, ["spec_id", "node_id"])
    rows = joined.groupBy("spec_id", "gen", "seg").agg(F.array_sort(F.collect_list(F.struct("pos", "node_id", "op", "kids", "ints", "text"))).alias("rows"))
    rows = rows.withColumn("at", F.map_from_entries(F.array_distinct(F.transform("rows", lambda r: F.struct(r["node_id"], F.array_min(F.transform(F.filter("rows", lambda q: q["node_id"] == r["node_id"]), lambda q: q["pos"])))))))
    back = F.transform("rows", lambda r: F.struct(r["op"].alias("op"), F.transform(r["kids"], lambda k: F.element_at("at", k)).alias("kids"), r["ints"].alias("ints"), r["text"].alias("text")).cast(NODE))
    return rows.select("spec_id", "gen", "seg", back.alias("nodes"))


def measures(spec: DataFrame) -> DataFrame:
    """spec_id, nodes and bytes before and after interning."""
    size = lambda n: F.length(n["op"]) + 4 * F.size(n["kids"]) + 8 * F.size(n["ints"]) + F.length(n["text"])
    before = spec.groupBy("spec_id").agg(F.sum(F.size("nodes")).cast("bigint").alias("n_before"), F.sum(F.aggregate("nodes", F.lit(0).cast("bigint"), lambda a, n: a + size(n))).alias("bytes_before"))
    nodes, _ = intern(spec)
    after = nodes.groupBy("spec_id").agg(F.count("*").alias("n_after"), F.sum((F.length("op") + 4 * F.size("kids") + 8 * F.size("ints") + F.length("text")).cast("bigint")).alias("bytes_after"))
    return before.join(after, "spec_id")
