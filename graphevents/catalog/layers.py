"""Layers with fixed weights in their relational form."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import kg
from ..gnn import relational as R
from .base import DIM, NET, TO_TREES, TYPES, Work, sentence_edges, with_notes

QUERIES: dict = {}

#: Fixed weights: a relation's score is its number's remainder by 3 over 2; a relation's gate and the attention vectors likewise.
SCORES = {r: (r % 3) / 2 for r in range(1, 13)}
GATES = {r: [(r + d) % 3 - 1 for d in range(DIM)] for r in range(1, 13)}
A1, A2 = [0.5, -0.25, 0.25, 0.0], [0.25, 0.25, -0.5, 0.5]


def nodes_and_edges(w: Work):
    """States of the nodes (md5 digits) and edges of all sentence graphs."""
    e = w.sentence_edges().select(F.col("sent_id").alias("g"), "i", "j", "rels")
    names = e.select("g", F.col("i").alias("n")).distinct()
    vec = kg.hash_vectors(names.select(F.col("n").alias("key")).distinct(), DIM).select(F.col("key").alias("n"), "dim", F.col("value").cast("double").alias("x"))
    return names.join(vec, "n").select("g", "n", "dim", "x"), e


GRAPH = (
    *TO_TREES, TYPES, NET, sentence_edges(),
    "ge AS MATERIALIZED (SELECT sent_id AS g, i, j, rels FROM se)",
    f"x0 AS MATERIALIZED (SELECT g, n, d AS dim, CAST(CAST(('0x' || md5(n)[d + 1]) AS INT) % 7 - 3 AS DOUBLE) AS x FROM (SELECT DISTINCT g, i AS n FROM ge), (SELECT CAST(unnest(range({DIM})) AS INT) AS d))",
)
WEIGHTS = (
    "el AS MATERIALIZED (SELECT g, i, j, exp(list_sum(list_transform(rels, lambda r: (r % 3) / 2.0))) AS z FROM ge)",
    "aw AS MATERIALIZED (SELECT g, i, j, z / sum(z) OVER (PARTITION BY g, i) AS a FROM el)",
)


def layer_sql(inp: str, out: str) -> str:
    return f"{out} AS MATERIALIZED (SELECT s.g, s.n, s.dim, s.x + coalesce(m.m, 0) AS x FROM {inp} s LEFT JOIN (SELECT aw.g, aw.i AS n, b.dim, sum(a * b.x) AS m FROM aw JOIN {inp} b ON b.g = aw.g AND b.n = aw.j GROUP BY ALL) m USING (g, n, dim))"


def rounded(df):
    """What is compared of the states of all graphs: for each graph and dimension the number of nodes, their sum, least and greatest."""
    total, low, high = (F.round(f("x") + 1e-7, 3) + 0.0 for f in (F.sum, F.min, F.max))  # off the edge where exact halves are rounded
    return df.groupBy("g", "dim").agg(F.count("*").alias("nodes"), total.alias("total"), low.alias("low"), high.alias("high"))


def sql_rounded(name: str) -> str:
    return f"SELECT g, dim, count(*) AS nodes, round(sum(x) + 1e-7, 3) + 0.0 AS total, round(min(x) + 1e-7, 3) + 0.0 AS low, round(max(x) + 1e-7, 3) + 0.0 AS high FROM {name} GROUP BY g, dim"


def weights(spark, sf):
    _, e = nodes_and_edges(Work(spark, sf))
    a = R.attention_weights(e, R.edge_logits(e, SCORES))
    return a.groupBy("g").agg(F.count("*").alias("edges"), F.count_distinct("i").alias("receivers"), F.round(F.sum("a"), 3).alias("total"), F.round(F.sum(F.col("a") * F.col("a")), 3).alias("squares"))


def attention(layers: int):
    def run(spark, sf):
        x, e = nodes_and_edges(Work(spark, sf))
        for _ in range(layers):
            x = R.edge_softmax_attention(x, e, SCORES)
        return rounded(x)

    return run


def conv(gate: str):
    def run(spark, sf):
        x, e = nodes_and_edges(Work(spark, sf))
        gates = GATES if gate == "diagonal" else {r: g[:1] for r, g in GATES.items()} if gate == "scalar" else {r: [(r + a + b) % 3 - 1 for a in range(DIM) for b in range(DIM)] for r in GATES}
        return rounded(R.edge_conditioned_conv(x, e, gates, gate))

    return run


GATE = (
    f"gt AS MATERIALIZED (SELECT rels, d, list_sum(list_transform(rels, lambda r: (r + d) % 3 - 1)) AS gate FROM (SELECT DISTINCT rels FROM ge), (SELECT CAST(unnest(range({2 * DIM - 1})) AS INT) AS d))",
    "gj AS MATERIALIZED (SELECT e.g, e.i AS n, e.rels, b.dim, sum(b.x) AS x FROM ge e JOIN x0 b ON b.g = e.g AND b.n = e.j GROUP BY ALL)",
)
QUERIES["gnn_edge_softmax_weights"] = (weights, with_notes(*GRAPH, *WEIGHTS) + "SELECT g, count(*) AS edges, count(DISTINCT i) AS receivers, round(sum(a), 3) AS total, round(sum(a * a), 3) AS squares FROM aw GROUP BY g")
QUERIES["gnn_edge_softmax_layer1"] = (attention(1), with_notes(*GRAPH, *WEIGHTS, layer_sql("x0", "x1")) + sql_rounded("x1"))
QUERIES["gnn_edge_softmax_layer2"] = (attention(2), with_notes(*GRAPH, *WEIGHTS, layer_sql("x0", "x1"), layer_sql("x1", "x2")) + sql_rounded("x2"))
for _gate, _sum in (
    ("scalar", "SELECT g, n, dim, sum(gate * x) AS m FROM gj JOIN gt ON gt.rels = gj.rels AND gt.d = 0 GROUP BY ALL"),
    ("diagonal", "SELECT g, n, dim, sum(gate * x) AS m FROM gj JOIN gt ON gt.rels = gj.rels AND gt.d = dim GROUP BY ALL"),
    ("matrix", f"SELECT g, n, t AS dim, sum(gate * x) AS m FROM gj, (SELECT CAST(unnest(range({DIM})) AS INT) AS t) JOIN gt ON gt.rels = gj.rels AND gt.d = dim + t GROUP BY ALL"),
):
    QUERIES[f"gnn_edge_conv_{_gate}"] = (conv(_gate), with_notes(*GRAPH, *GATE, f"cm AS MATERIALIZED ({_sum})", "y AS (SELECT s.g, s.n, s.dim, s.x + coalesce(m, 0) AS x FROM x0 s LEFT JOIN cm USING (g, n, dim))") + sql_rounded("y"))


def node_attention(spark, sf):
    x, e = nodes_and_edges(Work(spark, sf))
    return rounded(R.node_attention(x, e, A1, A2))


QUERIES["gnn_node_attention_fixed"] = (
    node_attention,
    with_notes(
        *GRAPH,
        f"uv AS MATERIALIZED (SELECT g, n, sum(x * {A1}[dim + 1]) AS u, sum(x * {A2}[dim + 1]) AS v FROM x0 GROUP BY g, n)",
        "nl AS (SELECT DISTINCT g, i, j FROM (SELECT g, i, j FROM ge UNION ALL SELECT DISTINCT g, n, n FROM x0))",
        "nz AS (SELECT nl.g, i, j, a.u + b.v AS r FROM nl JOIN uv a ON a.g = nl.g AND a.n = i JOIN uv b ON b.g = nl.g AND b.n = j)",
        "ne AS (SELECT g, i, j, exp(CASE WHEN r > 0 THEN r ELSE 0.2 * r END) AS z FROM nz)",
        "na AS MATERIALIZED (SELECT g, i, j, z / sum(z) OVER (PARTITION BY g, i) AS a FROM ne)",
        "y AS (SELECT na.g, i AS n, dim, sum(a * x) AS x FROM na JOIN x0 b ON b.g = na.g AND b.n = j GROUP BY ALL)",
    )
    + sql_rounded("y"),
)


def mean(norm: str):
    def run(spark, sf):
        x, e = nodes_and_edges(Work(spark, sf))
        return rounded(R.mean_neighbours(x, e, norm))

    return run


DEGREE = "dg AS MATERIALIZED (SELECT g, i, count(*) AS d FROM ge GROUP BY g, i)"
for _norm, _w in (("mean", "1.0 / a.d"), ("sym", "1.0 / sqrt(a.d * b.d)")):
    QUERIES[f"gnn_{_norm}_layer"] = (
        mean(_norm),
        with_notes(
            *GRAPH, DEGREE, f"aw AS MATERIALIZED (SELECT e.g, e.i, e.j, {_w} AS a FROM ge e JOIN dg a ON a.g = e.g AND a.i = e.i JOIN dg b ON b.g = e.g AND b.i = e.j)", layer_sql("x0", "y")
        )
        + sql_rounded("y"),
    )
#: Fixed weights of the full layer: relation vectors, the map of edge vectors to a logit (one hidden layer), the map of a node's own state, and
#: the projections into and out of the graph.
RELATION = {r: [(r + d) % 3 - 1 for d in range(DIM)] for r in range(1, 13)}
PSI_1, PSI_2 = [[(a + 2 * h) % 3 - 1 for h in range(DIM)] for a in range(DIM)], [[0.5 * ((h % 3) - 1)] for h in range(DIM)]
THETA_1, THETA_2 = [[(2 * a + h) % 3 - 1 for h in range(DIM)] for a in range(DIM)], [[0.25 * ((h + 2 * b) % 3 - 1) for b in range(DIM)] for h in range(DIM)]
INTO, OUT = [[0.5 * ((a + b) % 3 - 1) for b in range(DIM)] for a in range(DIM)], [[0.5 * ((2 * a + b) % 3 - 1) for b in range(DIM)] for a in range(DIM)]
INTO_BIAS, OUT_BIAS = [0.25 * (b % 2) for b in range(DIM)], [0.5 * (b % 3) for b in range(DIM)]


def sql_matrix(name: str, matrix: list[list[float]]) -> str:
    return f"{name} AS MATERIALIZED (SELECT * FROM (VALUES {', '.join(f'({i}, {j}, {float(v)}::DOUBLE)' for i, r in enumerate(matrix) for j, v in enumerate(r))}) AS v(dim, t, w))"


def sql_linear(inp: str, out: str, matrix: str, relu: bool = False, bias: str = "0.0") -> str:
    value = f"sum(x * w) + any_value({bias})"
    return f"{out} AS MATERIALIZED (SELECT g, n, t AS dim, {f'greatest({value}, 0.0)' if relu else value} AS x FROM {inp} JOIN {matrix} USING (dim) GROUP BY g, n, t)"


def biased(bias: list[float]) -> str:
    return f"{[float(b) for b in bias]}[t + 1]"


FULL_WEIGHTS = (
    sql_matrix("p1", PSI_1), sql_matrix("p2", PSI_2), sql_matrix("t1", THETA_1), sql_matrix("t2", THETA_2), sql_matrix("wi", INTO), sql_matrix("wo", OUT), sql_matrix("rv", [[0.0] * DIM, *RELATION.values()]),
    "fs AS MATERIALIZED (SELECT row_number() OVER () AS n, rels FROM (SELECT DISTINCT rels FROM ge))",
    "fv AS (SELECT 0 AS g, n, t AS dim, sum(w) AS x FROM (SELECT n, unnest(rels) AS r FROM fs) JOIN rv ON rv.dim = r GROUP BY n, t)",
    sql_linear("fv", "fh", "p1", relu=True), sql_linear("fh", "fz", "p2"),
    "fe AS MATERIALIZED (SELECT ge.g, i, j, exp(x) AS z FROM ge JOIN fs ON fs.rels = ge.rels JOIN fz ON fz.n = fs.n)",
    "aw AS MATERIALIZED (SELECT g, i, j, z / sum(z) OVER (PARTITION BY g, i) AS a FROM fe)",
)


def full_layer_sql(inp: str, out: str) -> tuple[str, ...]:
    own, message = f"{out}_own", f"{out}_m"
    return (
        sql_linear(inp, f"{out}_h", "t1", relu=True), sql_linear(f"{out}_h", own, "t2"),
        f"{message} AS MATERIALIZED (SELECT aw.g, aw.i AS n, b.dim, sum(a * b.x) AS m FROM aw JOIN {inp} b ON b.g = aw.g AND b.n = aw.j GROUP BY ALL)",
        f"{out} AS MATERIALIZED (SELECT s.g, s.n, s.dim, s.x + coalesce(m.m, 0) AS x FROM {own} s LEFT JOIN {message} m USING (g, n, dim))",
    )


def full_logits(e):
    return R.mlp_logits(e, RELATION, PSI_1, PSI_2)


def full_attention(spark, sf):
    x, e = nodes_and_edges(Work(spark, sf))
    logits = full_logits(e)
    for _ in range(2):
        x = R.edge_softmax_attention(x, e, logits, (THETA_1, THETA_2))
    return rounded(x)


def full_fused(spark, sf):
    """Text vectors projected into the graph, a full layer, and back by a projection and the residual."""
    w = Work(spark, sf)
    x, e = nodes_and_edges(w)
    tokens = token_vectors(w)
    known = R.linear(tokens.withColumnRenamed("h", "x").join(x.select("g", "n").distinct(), ["g", "n"], "left_semi"), INTO, INTO_BIAS)
    x = known.unionByName(x.join(tokens.select("g", "n").distinct(), ["g", "n"], "left_anti"))
    logits = full_logits(e)
    x = R.edge_softmax_attention(x, e, logits, (THETA_1, THETA_2))
    back = R.linear(x.filter(F.col("n").startswith("t:")), OUT, OUT_BIAS)
    return rounded(R.fuse(tokens, back).withColumnRenamed("h", "x"))


QUERIES["gnn_edge_softmax_full"] = (full_attention, with_notes(*GRAPH, *FULL_WEIGHTS, *full_layer_sql("x0", "x1"), *full_layer_sql("x1", "x2")) + sql_rounded("x2"))
QUERIES["gnn_identity"] = (lambda spark, sf: rounded(R.identity(nodes_and_edges(Work(spark, sf))[0])), with_notes(*GRAPH) + sql_rounded("x0"))


def token_vectors(w: Work):
    """Text vectors of all tokens: md5 digits of their forms."""
    t = w.sentences.select(F.col("sent_id").alias("g"), F.posexplode(F.split("text", " ")).alias("tok", "form"))
    vec = kg.hash_vectors(t.select(F.col("form").alias("key")).distinct(), DIM).select(F.col("key").alias("form"), "dim", F.col("value").cast("double").alias("h"))
    return t.join(vec, "form").select("g", F.concat(F.lit("t:"), F.col("tok").cast("string")).alias("n"), "dim", "h")


def fused_rows(spark, sf):
    """``g, n, dim, x``: text vectors of all tokens plus the states of their nodes after two layers."""
    w = Work(spark, sf)
    x, e = nodes_and_edges(w)
    for _ in range(2):
        x = R.edge_softmax_attention(x, e, SCORES)
    return R.fuse(token_vectors(w), x).withColumnRenamed("h", "x")


def fused_tokens(spark, sf):
    return rounded(fused_rows(spark, sf))


TOKENS = (
    "tf AS (SELECT sent_id AS g, generate_subscripts(w, 1) - 1 AS tok, unnest(w) AS form FROM (SELECT sent_id, string_split(text, ' ') AS w FROM note_sentences))",
    f"h0 AS MATERIALIZED (SELECT g, 't:' || tok AS n, d AS dim, CAST(('0x' || md5(form)[d + 1]) AS INT) % 7 - 3 AS h FROM tf, (SELECT CAST(unnest(range({DIM})) AS INT) AS d))",
)
QUERIES["gnn_fused_tokens"] = (
    fused_tokens,
    with_notes(
        *GRAPH, *WEIGHTS, layer_sql("x0", "x1"), layer_sql("x1", "x2"),
        *TOKENS,
        "y AS (SELECT h0.g, h0.n, h0.dim, h + coalesce(x, 0) AS x FROM h0 LEFT JOIN x2 USING (g, n, dim))",
    )
    + sql_rounded("y"),
)
QUERIES["gnn_fused_full"] = (
    full_fused,
    with_notes(
        *GRAPH, *FULL_WEIGHTS, *TOKENS,
        "hk AS MATERIALIZED (SELECT g, n, dim, h::DOUBLE AS x FROM h0 SEMI JOIN x0 USING (g, n))",
        sql_linear("hk", "hp", "wi", bias=biased(INTO_BIAS)),
        "xs AS MATERIALIZED (SELECT g, n, dim, x FROM hp UNION ALL SELECT g, n, dim, x FROM x0 WHERE NOT starts_with(n, 't:'))",
        *full_layer_sql("xs", "x1"),
        "xt AS MATERIALIZED (SELECT * FROM x1 WHERE starts_with(n, 't:'))", sql_linear("xt", "xo", "wo", bias=biased(OUT_BIAS)),
        "y AS (SELECT h0.g, h0.n, h0.dim, h + coalesce(x, 0) AS x FROM h0 LEFT JOIN xo USING (g, n, dim))",
    )
    + sql_rounded("y"),
)
