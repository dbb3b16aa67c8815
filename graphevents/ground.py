"""Mapping sentences to concepts."""

from __future__ import annotations

from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .sources.tables import load

#: Most bytes of dictionary that are broadcast.
BROADCAST_BYTES = 64 << 20


def dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``surface, n_tok, concept_id``: names in lower case. A part's name stands for its family and for each of its parts: ambiguous."""
    parts = []
    for table, key, prefix, name in (("customer", "c_custkey", "C:", "c_name"), ("supplier", "s_suppkey", "S:", "s_name"), ("part", "p_partkey", "P:", "p_name"), ("nation", "n_nationkey", "N:", "n_name"), ("region", "r_regionkey", "R:", "r_name")):
        parts.append(load(spark, sf_dir, table).select(F.lower(name).alias("surface"), F.concat(F.lit(prefix), F.col(key).cast("string")).alias("concept_id")))
    family = load(spark, sf_dir, "part").select("p_name").distinct()
    parts.append(family.select(F.lower("p_name").alias("surface"), F.concat(F.lit("F:"), "p_name").alias("concept_id")))
    parts.append(family.select(F.lower(F.element_at(F.split("p_name", " "), -1)).alias("s")).distinct().select(F.col("s").alias("surface"), F.concat(F.lit("H:"), "s").alias("concept_id")))
    out = reduce(DataFrame.unionByName, parts)
    return out.withColumn("n_tok", F.size(F.split("surface", " "))).select("surface", "n_tok", "concept_id")


def ngrams(sents: DataFrame, longest: int = 2) -> DataFrame:
    """``sent_id, tok_from, tok_to, surface`` for all stretches of up to ``longest`` tokens of blank-separated text."""
    words = F.split(F.lower("text"), " ")
    w = sents.select("sent_id", words.alias("w"))
    w = w.select("sent_id", "w", F.explode(F.sequence(F.lit(1), F.size("w"))).alias("a"), F.lit(longest).alias("most"))
    w = w.select("sent_id", "w", "a", F.explode(F.sequence(F.lit(1), F.least("most", F.size("w") - F.col("a") + 1))).alias("k"))
    return w.select("sent_id", (F.col("a") - 1).alias("tok_from"), (F.col("a") + F.col("k") - 2).alias("tok_to"), F.array_join(F.slice("w", F.col("a"), F.col("k")), " ").alias("surface"))


def match_ngrams(sents: DataFrame, words: DataFrame, longest: int = 2) -> DataFrame:
    """All matches: ``sent_id, tok_from, tok_to, concept_id``. Catalyst broadcasts the dictionary below its limit; beyond it, both
    sides meet by surface with a Bloom filter at run time."""
    return ngrams(sents, longest).join(words.select("surface", "concept_id"), "surface").select("sent_id", "tok_from", "tok_to", "concept_id")


def resolve_overlaps(matches: DataFrame) -> DataFrame:
    """Leftmost, then longest, without overlap: one pass over a sentence's spans, kept as a sorted array of bounded length."""
    spans = matches.select("sent_id", "tok_from", "tok_to").distinct().groupBy("sent_id").agg(F.array_sort(F.collect_list(F.struct("tok_from", (-F.col("tok_to")).alias("neg_to")))).alias("spans"))
    start = F.struct(F.array().cast("array<struct<a:int,b:int>>").alias("kept"), F.lit(-1).alias("end"))

    def step(state, s):
        fits = s["tok_from"] > state["end"]
        more = F.concat(state["kept"], F.array(F.struct(s["tok_from"].alias("a"), (-s["neg_to"]).alias("b"))))
        return F.struct(F.when(fits, more).otherwise(state["kept"]).alias("kept"), F.when(fits, -s["neg_to"]).otherwise(state["end"]).alias("end"))

    chosen = spans.select("sent_id", F.explode(F.aggregate("spans", start, step, lambda s: s["kept"])).alias("x"))
    return chosen.select("sent_id", F.col("x.a").alias("tok_from"), F.col("x.b").alias("tok_to")).join(matches, ["sent_id", "tok_from", "tok_to"])


def match_trie(sents: DataFrame, words: list[tuple[str, str]], longest: int = 8) -> DataFrame:
    """The same matches as ``resolve_overlaps(match_ngrams())`` with no shuffle: a trie of words, broadcast, walked in Arrow batches.
    ``words`` are (surface, concept); their total size is checked."""
    if sum(len(a) + len(b) + 64 for a, b in words) > BROADCAST_BYTES:
        raise ValueError("the dictionary is too large to broadcast: use match_ngrams")
    trie: dict = {}
    for surface, concept in words:
        node = trie
        for w in surface.split(" "):
            node = node.setdefault(w, {})
        node.setdefault("", []).append(concept)
    shared = sents.sparkSession.sparkContext.broadcast(trie)

    def run(batches):
        root = shared.value
        for batch in batches:
            out = ([], [], [], [])
            for sid, text in zip(batch.column("sent_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                tokens, at = text.lower().split(" "), 0
                while at < len(tokens):
                    node, best, k = root, None, at
                    while k < len(tokens) and (node := node.get(tokens[k])) is not None:
                        k += 1
                        best = (k, node[""]) if "" in node else best
                    for c in best[1] if best else ():
                        for column, v in zip(out, (sid, at, best[0] - 1, c), strict=True):
                            column.append(v)
                    at = best[0] if best else at + 1
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int32()), pa.array(out[2], pa.int32()), pa.array(out[3], pa.string())], ["sent_id", "tok_from", "tok_to", "concept_id"])

    return sents.select("sent_id", "text").mapInArrow(run, "sent_id long, tok_from int, tok_to int, concept_id string")


def disambiguate(matches: DataFrame, edges: DataFrame | None = None, policy: str = "neighbours") -> DataFrame:
    """One concept a span: ``all`` keeps every one, ``lowest`` the least id, ``neighbours`` the one with most edges to the sentence's other
    candidates (then the least id)."""
    span = Window.partitionBy("sent_id", "tok_from", "tok_to")
    if policy == "all":
        return matches
    if policy == "lowest":
        return matches.groupBy("sent_id", "tok_from", "tok_to").agg(F.min("concept_id").alias("concept_id"))
    other = matches.select("sent_id", F.col("tok_from").alias("f2"), F.col("concept_id").alias("c2"))
    pairs = matches.join(other, "sent_id").filter("tok_from <> f2")
    both = edges.select("src", "dst").union(edges.select("dst", "src")).distinct()
    near = pairs.join(both, (F.col("concept_id") == F.col("src")) & (F.col("c2") == F.col("dst")), "left_semi").groupBy("sent_id", "tok_from", "tok_to", "concept_id").agg(F.count_distinct("c2").alias("near"))
    ranked = matches.join(near, ["sent_id", "tok_from", "tok_to", "concept_id"], "left").withColumn("near", F.coalesce("near", F.lit(0)))
    return ranked.withColumn("r", F.row_number().over(span.orderBy(F.desc("near"), "concept_id"))).filter("r = 1").select("sent_id", "tok_from", "tok_to", "concept_id")


def align(matches: DataFrame, how: str = "head") -> DataFrame:
    """``sent_id, tok, concept_id``: a match stands on its last token, or on all of its tokens."""
    if how == "head":
        return matches.select("sent_id", F.col("tok_to").alias("tok"), "concept_id")
    return matches.select("sent_id", F.explode(F.sequence("tok_from", "tok_to")).alias("tok"), "concept_id")


def terminals(matches: DataFrame) -> DataFrame:
    return matches.select(F.col("concept_id").alias("node")).distinct()


def coverage(tokens: DataFrame, aligned: DataFrame) -> DataFrame:
    """``tokens, grounded``: how many tokens there are and how many have a concept."""
    hit = aligned.select("sent_id", "tok").distinct().withColumn("hit", F.lit(1))
    return tokens.join(hit, ["sent_id", "tok"], "left").agg(F.count("*").alias("tokens"), F.count("hit").alias("grounded"))


def match_phrases(docs: DataFrame, phrases: DataFrame, head: int = 4) -> DataFrame:
    """``doc_id, item_id`` where a whole phrase occurs in a text: they meet by the phrase's first words, then the text is checked."""
    words = F.split(F.regexp_replace("text", r"\s+", " "), " ")
    first = lambda w: F.array_join(F.slice(w, 1, head), " ")
    p = phrases.select("item_id", F.regexp_replace("text", r"\s+", " ").alias("phrase"), first(words).alias("k"))
    d = docs.select("doc_id", F.regexp_replace("text", r"\s+", " ").alias("plain"), words.alias("w"))
    d = d.select("doc_id", "plain", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - head + 1, F.lit(1))), lambda i: F.array_join(F.slice("w", i, head), " ")))).alias("k"))
    hits = d.join(F.broadcast(p), "k") if phrases.count() < 100_000 else d.join(p, "k")
    return hits.filter(F.contains("plain", "phrase")).select("doc_id", "item_id").distinct()
