"""Sentence graphs: concepts of the tree, tokens that mention them, semantic types and their relations."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kg import HAS_TYPE, MENTIONS


def concept_edges_of(trees: DataFrame, kg_edges: DataFrame, induce: str = "tree") -> DataFrame:
    """``sent_id, src, rel, dst``: relations of the tree's edges, or (``full``) all relations among the tree's nodes."""
    if induce == "tree":
        steps = trees.filter("parent is not null").select("sent_id", F.col("node").alias("x"), F.col("parent").alias("y"))
    else:
        n = trees.select("sent_id", F.col("node").alias("x")).distinct()
        steps = n.join(n.select("sent_id", F.col("x").alias("y")), "sent_id").filter("x <> y")
    k = kg_edges.select("src", "rel", "dst")
    down = steps.join(k, (F.col("x") == F.col("src")) & (F.col("y") == F.col("dst")))
    if induce == "tree":
        down = down.unionByName(steps.join(k, (F.col("y") == F.col("src")) & (F.col("x") == F.col("dst"))))
    return down.select("sent_id", "src", "rel", "dst").distinct()


def token_edges(aligned: DataFrame, trees: DataFrame) -> DataFrame:
    """Token nodes ``t:<place>`` joined with their concepts."""
    here = trees.select("sent_id", F.col("node").alias("concept_id")).distinct()
    return aligned.join(here, ["sent_id", "concept_id"], "left_semi").select("sent_id", F.concat(F.lit("t:"), F.col("tok").cast("string")).alias("src"), F.lit(MENTIONS).alias("rel"), F.col("concept_id").alias("dst")).distinct()


def type_edges(trees: DataFrame, types: DataFrame) -> DataFrame:
    """Concepts joined with their types, once a sentence."""
    here = trees.select("sent_id", F.col("node").alias("concept_id")).distinct()
    return here.join(types, "concept_id").select("sent_id", F.col("concept_id").alias("src"), F.lit(HAS_TYPE).alias("rel"), F.col("sty").alias("dst"))


def type_type_edges(concept_to_type: DataFrame, net: DataFrame) -> DataFrame:
    """Relations between the types of a sentence. Types of a sentence are few; the network has at most types^2 x relations rows."""
    sty = concept_to_type.select("sent_id", F.col("dst").alias("sty")).distinct()
    known = net.select("sty_src", "srel", "sty_dst").distinct()
    left = sty.join(F.broadcast(known), F.col("sty") == F.col("sty_src")).select("sent_id", "sty_src", "srel", "sty_dst")
    return left.join(sty.withColumnRenamed("sty", "sty_dst"), ["sent_id", "sty_dst"]).select("sent_id", F.col("sty_src").alias("src"), F.col("srel").alias("rel"), F.col("sty_dst").alias("dst"))


def sentence_edges(trees: DataFrame, aligned: DataFrame, kg_edges: DataFrame, types: DataFrame | None, net: DataFrame | None, induce: str = "tree") -> DataFrame:
    """``sent_id, i, j, rels``: all edges of the sentence graphs, both ways, with the set of relations of each ordered pair.

    ``types=None`` leaves out the upper level. A sentence without concepts has no rows: its tokens pass through every layer.
    """
    parts = [concept_edges_of(trees, kg_edges, induce), token_edges(aligned, trees)]
    if types is not None:
        up = type_edges(trees, types)
        parts.append(up)
        if net is not None:
            parts.append(type_type_edges(up, net))
    one = reduce(DataFrame.unionByName, parts)
    both = one.unionByName(one.select("sent_id", F.col("dst").alias("src"), "rel", F.col("src").alias("dst")))
    return both.filter("src <> dst").groupBy("sent_id", F.col("src").alias("i"), F.col("dst").alias("j")).agg(F.sort_array(F.collect_set("rel")).alias("rels"))


def nodes_of(edges: DataFrame) -> DataFrame:
    """``sent_id, node, kind``."""
    kind = F.when(F.col("i").startswith("t:"), "token").when(F.col("i").rlike("^[A-Z]:"), "concept").otherwise("type")
    return edges.select("sent_id", F.col("i").alias("node"), kind.alias("kind")).distinct()


def sizes(edges: DataFrame) -> DataFrame:
    n = nodes_of(edges).groupBy("sent_id").agg(*[F.count_if(F.col("kind") == k).alias(f"{k}s") for k in ("token", "concept", "type")])
    return n.join(edges.groupBy("sent_id").agg(F.count("*").alias("edges")), "sent_id")
