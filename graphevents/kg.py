"""The two-level knowledge graph: concepts and their relations below, semantic types and theirs above."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .sources.tables import load

RELATIONS = {
    "in_region": 1, "cust_nation": 2, "supp_nation": 3, "family": 4, "brand": 5, "head": 6, "placed_by": 7, "contains": 8, "served_by": 9, "supplied_by": 10,
}
MENTIONS, HAS_TYPE, INVERSE = 11, 12, 12

#: Relation: table, source column, its prefix, target column, its prefix.
SOURCES = (
    ("in_region", "nation", "n_nationkey", "N:", "n_regionkey", "R:"),
    ("cust_nation", "customer", "c_custkey", "C:", "c_nationkey", "N:"),
    ("supp_nation", "supplier", "s_suppkey", "S:", "s_nationkey", "N:"),
    ("family", "part", "p_partkey", "P:", "p_name", "F:"),
    ("brand", "part", "p_partkey", "P:", "p_brand", "B:"),
    ("placed_by", "orders", "o_orderkey", "O:", "o_custkey", "C:"),
    ("contains", "lineitem", "l_orderkey", "O:", "l_partkey", "P:"),
    ("served_by", "lineitem", "l_orderkey", "O:", "l_suppkey", "S:"),
    ("supplied_by", "lineitem", "l_partkey", "P:", "l_suppkey", "S:"),
)
#: Types besides the class of a node: table, key, prefix, column, prefix of the type.
TYPE_SOURCES = (
    ("part", "p_partkey", "P:", "p_type", "kind:"),
    ("customer", "c_custkey", "C:", "c_mktsegment", "segment:"),
    ("orders", "o_orderkey", "O:", "o_orderpriority", "priority:"),
    ("orders", "o_orderkey", "O:", "o_orderstatus", "status:"),
)


def concept_edges(spark: SparkSession, sf_dir: str, relations: tuple[str, ...] | None = None) -> DataFrame:
    """``src, rel, dst`` once each. Each relation scans two columns of one table; only lineitem's can repeat pairs, but names repeat, too."""
    parts = []
    for name, table, a, pa, b, pb in SOURCES:
        if relations is None or name in relations:
            t = load(spark, sf_dir, table)
            parts.append(t.select(F.concat(F.lit(pa), F.col(a).cast("string")).alias("src"), F.lit(RELATIONS[name]).alias("rel"), F.concat(F.lit(pb), F.col(b).cast("string")).alias("dst")))
    if relations is None or "head" in relations:
        p = load(spark, sf_dir, "part").select("p_name").distinct()
        parts.append(p.select(F.concat(F.lit("F:"), "p_name").alias("src"), F.lit(RELATIONS["head"]).alias("rel"), F.concat(F.lit("H:"), F.element_at(F.split("p_name", " "), -1)).alias("dst")))
    return reduce(DataFrame.unionByName, parts).dropDuplicates(["src", "rel", "dst"])


def nodes_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct()


def concept_types(spark: SparkSession, sf_dir: str, edges: DataFrame | None = None) -> DataFrame:
    """``concept_id, sty``: the class of each node of the network and the categories of its row."""
    nodes = nodes_of(concept_edges(spark, sf_dir) if edges is None else edges)
    classes = nodes.select(F.col("node").alias("concept_id"), F.concat(F.lit("class:"), F.substring("node", 1, 1)).alias("sty"))
    parts = [classes]
    for table, key, prefix, column, kind in TYPE_SOURCES:
        parts.append(load(spark, sf_dir, table).select(F.concat(F.lit(prefix), F.col(key).cast("string")).alias("concept_id"), F.concat(F.lit(kind), F.col(column)).alias("sty")))
    return reduce(DataFrame.unionByName, parts).distinct()


def lift_types(edges: DataFrame, types: DataFrame, support: int = 1) -> DataFrame:
    """The semantic network: type pairs joined by at least ``support`` edges of a relation. Edges are summed by (source's types, relation,
    target) before the second join, which keeps the product of types small."""
    src = types.select(F.col("concept_id").alias("src"), F.col("sty").alias("sty_src"))
    dst = types.select(F.col("concept_id").alias("dst"), F.col("sty").alias("sty_dst"))
    half = edges.join(src, "src").groupBy("sty_src", "rel", "dst").agg(F.count("*").alias("k"))
    return half.join(dst, "dst").groupBy("sty_src", F.col("rel").alias("srel"), "sty_dst").agg(F.sum("k").alias("support")).filter(F.col("support") >= support)


def both_ways(edges: DataFrame, inverse: str = "same") -> DataFrame:
    """Edges in both directions; ``distinct`` gives the way back a relation of its own."""
    if inverse not in ("same", "distinct"):
        raise ValueError(inverse)
    back = F.col("rel") + (INVERSE if inverse == "distinct" else 0)
    return edges.unionByName(edges.select(F.col("dst").alias("src"), back.alias("rel"), F.col("src").alias("dst")))


def merge_relations(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(``src, dst, relset_id``, ``relset_id, rels``). The ids are ranks of the distinct sets, a table of a few hundred rows."""
    sets = edges.groupBy("src", "dst").agg(F.sort_array(F.collect_set("rel")).alias("rels"))
    distinct = sets.select("rels").distinct().withColumn("relset_id", F.row_number().over(Window.orderBy("rels")))
    return sets.join(F.broadcast(distinct), "rels").select("src", "dst", "relset_id"), distinct.select("relset_id", "rels")


def stats(edges: DataFrame, types: DataFrame, net: DataFrame, terminals: DataFrame) -> DataFrame:
    one = lambda df, name, what: df.agg(what.cast("long").alias("value")).select(F.lit(name).alias("measure"), "value")
    return reduce(DataFrame.unionByName, [
        one(nodes_of(edges), "concepts", F.count("*")), one(edges, "edges", F.count("*")), one(edges, "relations", F.count_distinct("rel")),
        one(types, "types", F.count_distinct("sty")), one(net, "type_relations", F.count_distinct("srel")), one(net, "type_edges", F.count("*")),
        one(terminals, "terminals", F.count("*")),
    ])


def neighbours_in(edges: DataFrame, terminals: DataFrame) -> DataFrame:
    """``node, n``: distinct neighbours in the terminal set, in both directions."""
    k = terminals.select(F.col("node").alias("dst"))
    return both_ways(edges).select("src", "dst").join(k, "dst", "left_semi").groupBy(F.col("src").alias("node")).agg(F.count_distinct("dst").alias("n"))


def lexical_edges(tokens: DataFrame, min_df: int = 5, min_pair: int = 2) -> DataFrame:
    """A network of words from ``doc_id, pos, word``: words of at least three letters in at least ``min_df`` documents, joined where
    one follows the other at least ``min_pair`` times. Neighbours come from a window over the document, not from a join."""
    words = tokens.filter(F.length("word") >= 3)
    vocabulary = words.select("doc_id", "word").distinct().groupBy("word").agg(F.count("*").alias("df")).filter(F.col("df") >= min_df).select("word")
    follow = tokens.withColumn("next", F.lead("word").over(Window.partitionBy("doc_id").orderBy("pos"))).groupBy("word", "next").agg(F.count("*").alias("n")).filter(F.col("n") >= min_pair)
    pairs = follow.join(vocabulary, "word", "left_semi").join(vocabulary.select(F.col("word").alias("next")), "next", "left_semi")
    return pairs.select(F.col("word").alias("src"), F.col("next").alias("dst"), "n")


def hash_vectors(keys: DataFrame, dim: int = 8) -> DataFrame:
    """``key, dim, value``: portable vectors with entries -3 to 3, from md5 digits."""
    digit = F.conv(F.substring(F.md5("key"), F.col("dim") + 1, 1), 16, 10).cast("int")
    return keys.select("key", F.explode(F.sequence(F.lit(0), F.lit(dim - 1))).alias("dim")).withColumn("value", digit % 7 - 3)


def edge_vector_sums(relsets: DataFrame, rel_vectors: DataFrame) -> DataFrame:
    """``relset_id, dim, value``: the sum of the vectors of a set's relations."""
    return relsets.select("relset_id", F.explode("rels").alias("rel")).join(F.broadcast(rel_vectors), "rel").groupBy("relset_id", "dim").agg(F.sum("value").alias("value"))
