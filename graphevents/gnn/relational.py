"""Graph layers as DataFrame plans, for one large graph or as the checkable form of the kernels.

Node states are rows ``g, n, dim, x`` (graph, node, dimension, value); edges ``g, i, j, rels`` give the receiver i and sender j. Edge
vectors are sums over the relation set of an edge, so everything that depends on them is computed once per distinct set - a few
hundred rows that are broadcast - and joined to the edges. One shuffle by receiver a layer.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def relset_key(rels) -> F.Column:
    return F.array_join(rels.cast("array<string>"), ",")


def edge_logits(edges: DataFrame, rel_scores: dict[int, float]) -> DataFrame:
    """``key, logit`` per distinct relation set: the scalar map of the summed edge vector, here linear with a score a relation."""
    score = F.create_map(*[x for k, v in sorted(rel_scores.items()) for x in (F.lit(k), F.lit(float(v)))])
    sets = edges.select("rels").distinct()
    return sets.select(relset_key(F.col("rels")).alias("key"), F.aggregate("rels", F.lit(0.0), lambda a, r: a + F.coalesce(F.try_element_at(score, r), F.lit(0.0))).alias("logit"))


def attention_weights(edges: DataFrame, logits: DataFrame) -> DataFrame:
    """``g, i, j, a``: the softmax of the logits over the senders of each receiver, shifted by the largest."""
    own = Window.partitionBy("g", "i")
    e = edges.withColumn("key", relset_key(F.col("rels"))).join(F.broadcast(logits), "key")
    e = e.withColumn("z", F.exp(F.col("logit") - F.max("logit").over(own)))
    return e.select("g", "i", "j", (F.col("z") / F.sum("z").over(own)).alias("a"))


def weighted_sum(nodes: DataFrame, weights: DataFrame) -> DataFrame:
    """``g, n, dim, m``: for each receiver the weighted sum of its senders' states."""
    sender = nodes.select("g", F.col("n").alias("j"), "dim", "x")
    return weights.join(sender, ["g", "j"]).groupBy("g", F.col("i").alias("n"), "dim").agg(F.sum(F.col("a") * F.col("x")).alias("m"))


def mlp_logits(edges: DataFrame, vectors: dict[int, list[float]], first: list[list[float]], second: list[list[float]]) -> DataFrame:
    """``key, logit`` per distinct relation set: an MLP of the sum of its relations' vectors, evaluated once a set."""
    flat = [(r, d, float(v)) for r, vec in vectors.items() for d, v in enumerate(vec)]
    table = F.broadcast(edges.sparkSession.createDataFrame(flat, "rel int, dim int, w double"))
    sets = edges.select("rels").distinct().select(relset_key(F.col("rels")).alias("n"), F.explode("rels").alias("rel"))
    summed = sets.join(table, "rel").groupBy("n", "dim").agg(F.sum("w").alias("x")).withColumn("g", F.lit(0))
    return mlp(summed, first, second).select(F.col("n").alias("key"), F.col("x").alias("logit"))


def linear(nodes: DataFrame, matrix: list[list[float]], bias: list[float] | None = None) -> DataFrame:
    """``x`` times a fixed matrix, plus a bias, with ReLU left to the caller. The matrix is broadcast as a small table."""
    rows = [(i, j, float(v)) for i, r in enumerate(matrix) for j, v in enumerate(r)]
    m = nodes.sparkSession.createDataFrame(rows, "dim int, to int, w double")
    out = nodes.join(F.broadcast(m), "dim").groupBy("g", "n", F.col("to").alias("dim")).agg(F.sum(F.col("x") * F.col("w")).alias("x"))
    return out if bias is None else out.withColumn("x", F.col("x") + F.element_at(F.array(*[F.lit(float(b)) for b in bias]), F.col("dim") + 1))


def mlp(nodes: DataFrame, first: list[list[float]], second: list[list[float]]) -> DataFrame:
    hidden = linear(nodes, first).withColumn("x", F.greatest(F.col("x"), F.lit(0.0)))
    return linear(hidden, second)


def add(own: DataFrame, messages: DataFrame) -> DataFrame:
    """The self term plus what arrives; a node without senders keeps its self term."""
    return own.join(messages, ["g", "n", "dim"], "left").select("g", "n", "dim", (F.col("x") + F.coalesce("m", F.lit(0.0))).alias("x"))


def edge_softmax_attention(nodes: DataFrame, edges: DataFrame, rel_scores: dict[int, float] | DataFrame, theta: tuple | None = None) -> DataFrame:
    """One layer: a node's own state through an MLP (identity without one) plus the softmax-weighted states of its senders.
    ``rel_scores``: a score a relation, or the logits of relation sets."""
    own = mlp(nodes, *theta) if theta else nodes
    logits = rel_scores if isinstance(rel_scores, DataFrame) else edge_logits(edges, rel_scores)
    return add(own, weighted_sum(nodes, attention_weights(edges, logits)))


def edge_conditioned_conv(nodes: DataFrame, edges: DataFrame, gates: dict[int, list[float]], gate: str = "scalar", theta: tuple | None = None) -> DataFrame:
    """One layer: own state plus senders' states, each multiplied by the gate of its edge (a scalar, one a dimension, or a matrix
    given row by row), not normalised. Gates of a relation set are sums over its relations."""
    own = mlp(nodes, *theta) if theta else nodes
    width = len(next(iter(gates.values())))
    flat = [(k, d, float(v)) for k, g in gates.items() for d, v in enumerate(g)]
    table = F.broadcast(nodes.sparkSession.createDataFrame(flat, "rel int, part int, w double"))
    e = edges.withColumn("key", relset_key(F.col("rels")))
    by_set = F.broadcast(e.select("key", "rels").distinct().select("key", F.explode("rels").alias("rel")).join(table, "rel").groupBy("key", "part").agg(F.sum("w").alias("w")))
    sender = nodes.select("g", F.col("n").alias("j"), "dim", "x")
    s = e.join(sender, ["g", "j"])
    if gate == "scalar":
        got = s.join(by_set.filter("part = 0"), "key").withColumn("to", F.col("dim"))
    elif gate == "diagonal":
        got = s.join(by_set, (s["key"] == by_set["key"]) & (F.col("dim") == F.col("part"))).withColumn("to", F.col("dim"))
    else:
        d = int(width**0.5)
        got = s.join(by_set, (s["key"] == by_set["key"]) & (F.col("dim") == F.floor(F.col("part") / d))).withColumn("to", (F.col("part") % d).cast("int"))
    return add(own, got.groupBy("g", F.col("i").alias("n"), F.col("to").alias("dim")).agg(F.sum(F.col("x") * F.col("w")).alias("m")))


def node_attention(nodes: DataFrame, edges: DataFrame, a1: list[float], a2: list[float], slope: float = 0.2) -> DataFrame:
    """One head without a projection: logits leaky(a1.x_i + a2.x_j) over the senders and the node itself; edge vectors are unused."""
    pick = lambda a: F.element_at(F.array(*[F.lit(float(v)) for v in a]), F.col("dim") + 1)
    s = nodes.groupBy("g", "n").agg(F.sum(F.col("x") * pick(a1)).alias("u"), F.sum(F.col("x") * pick(a2)).alias("v"))
    e = edges.select("g", "i", "j").union(nodes.select("g", F.col("n").alias("i"), F.col("n").alias("j"))).distinct()
    e = e.join(s.select("g", F.col("n").alias("i"), "u"), ["g", "i"]).join(s.select("g", F.col("n").alias("j"), "v"), ["g", "j"])
    z = F.col("u") + F.col("v")
    e = e.withColumn("z", F.when(z > 0, z).otherwise(slope * z))
    own = Window.partitionBy("g", "i")
    e = e.withColumn("z", F.exp(F.col("z") - F.max("z").over(own)))
    w = e.select("g", "i", "j", (F.col("z") / F.sum("z").over(own)).alias("a"))
    return weighted_sum(nodes, w).withColumnRenamed("m", "x")


def mean_neighbours(nodes: DataFrame, edges: DataFrame, norm: str = "mean") -> DataFrame:
    """Own state plus the senders' mean, or their sum over the root of both degrees."""
    deg = edges.groupBy("g", F.col("i").alias("n")).agg(F.count("*").alias("deg"))
    e = edges.join(deg.select("g", F.col("n").alias("i"), F.col("deg").alias("di")), ["g", "i"])
    if norm == "mean":
        w = e.select("g", "i", "j", (1.0 / F.col("di")).alias("a"))
    else:
        w = e.join(deg.select("g", F.col("n").alias("j"), F.col("deg").alias("dj")), ["g", "j"]).select("g", "i", "j", (1.0 / F.sqrt(F.col("di") * F.col("dj"))).alias("a"))
    return add(nodes, weighted_sum(nodes, w))


def identity(nodes: DataFrame) -> DataFrame:
    return nodes


def fuse(tokens: DataFrame, states: DataFrame) -> DataFrame:
    """Text vectors ``g, n, dim, h`` plus the states of their token nodes; a token without a node is unchanged."""
    return tokens.join(states, ["g", "n", "dim"], "left").select("g", "n", "dim", (F.col("h") + F.coalesce("x", F.lit(0.0))).alias("h"))
