"""What several queries share: derived tables, kept per application and folder, and the same tables as SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import ground, kg, sentgraph, tree
from ..operators.components import checkpointed
from ..sources import notes

THRESHOLD, LEVELS, DIM = 10, 7, 4
_KEPT: dict[tuple, DataFrame] = {}


def forget() -> None:
    """Drop what is kept, so that the next query derives it anew."""
    _KEPT.clear()


class Work:
    """Derived tables of one folder, made when first asked for."""

    def __init__(self, spark: SparkSession, sf_dir: str) -> None:
        self.spark, self.sf = spark, sf_dir

    def kept(self, name: str, make) -> DataFrame:
        key = (self.spark.sparkContext.applicationId, self.sf, name)
        if key not in _KEPT:
            _KEPT[key] = checkpointed(make())
        return _KEPT[key]

    @property
    def lines(self):
        return self.kept("lines", lambda: notes.lines(self.spark, self.sf).drop("q", "plain"))

    @property
    def rendered(self):
        """The lines as a plan, for what reads them once: only the columns in use are made, nothing is written."""
        return notes.lines(self.spark, self.sf)

    @property
    def edges(self):
        return self.kept("edges", lambda: kg.concept_edges(self.spark, self.sf))

    @property
    def types(self):
        return kg.concept_types(self.spark, self.sf, self.edges)

    @property
    def net(self):
        return self.kept("net", lambda: kg.lift_types(self.edges, self.types, support=20))

    @property
    def terminals(self):
        return self.kept("terminals", lambda: notes.terminals(self.rendered))

    @property
    def codes(self):
        return self.kept("codes", lambda: notes.terminal_codes(self.rendered))

    def pruned(self, threshold: int = THRESHOLD):
        return self.kept(f"pruned{threshold}", lambda: tree.prune(self.edges, self.terminals, threshold))

    @property
    def forest(self):
        return self.kept("forest", lambda: tree.bfs_forest(self.pruned(), tree.choose_roots(self.pruned(), self.terminals)))

    @property
    def aligned(self):
        """``sent_id, tok, concept_id`` of the concepts that a sentence names."""
        part = lambda cond, key, tok: F.when(F.expr(cond), F.struct(F.expr(key).alias("concept_id"), F.expr(tok).cast("int").alias("tok")))
        rows = F.array(
            part("kind IN (0, 2)", "concat('C:', o_custkey)", "d"), part("kind IN (0, 1, 3)", "concat('S:', l_suppkey)", "supp_at"),
            part("true", "concat('P:', l_partkey)", "part_at + 1"), part("kind = 3", "concat('P:', next_part)", "next_at + 1"),
        )
        return self.lines.select("sent_id", F.explode(rows).alias("x")).filter("x is not null").select("sent_id", "x.tok", "x.concept_id")

    @property
    def trees(self):
        return self.kept("trees", lambda: tree.sentence_trees(self.aligned, self.forest))

    def sentence_edges(self, types: bool = True, induce: str = "tree"):
        return self.kept(f"sg{types}{induce}", lambda: sentgraph.sentence_edges(self.trees, self.aligned, self.edges, self.types if types else None, self.net if types else None, induce))

    @property
    def sentences(self):
        return notes.sentences(self.lines)

    @property
    def matches(self):
        return self.kept("matches", lambda: ground.match_ngrams(self.sentences, ground.dictionary(self.spark, self.sf)))


# The same tables as DuckDB common table expressions.
def union(parts: list[str]) -> str:
    return " UNION ALL ".join(parts)


EDGES = (
    "ce AS MATERIALIZED (SELECT DISTINCT src, rel, dst FROM ("
    + union([f"SELECT '{pa}' || {a} AS src, {kg.RELATIONS[n]} AS rel, '{pb}' || {b} AS dst FROM {t}" for n, t, a, pa, b, pb in kg.SOURCES] + ["SELECT 'F:' || p_name, 6, 'H:' || split_part(p_name, ' ', 2) FROM part"])
    + "))"
)
TYPES = (
    "ct AS MATERIALIZED (SELECT DISTINCT concept_id, sty FROM (SELECT n AS concept_id, 'class:' || n[1] AS sty FROM (SELECT src AS n FROM ce UNION SELECT dst FROM ce) UNION ALL "
    + union([f"SELECT '{p}' || {k}, '{kind}' || {c} FROM {t}" for t, k, p, c, kind in kg.TYPE_SOURCES])
    + "))"
)
BOTH = "ue AS MATERIALIZED (SELECT src, dst FROM ce WHERE src <> dst UNION SELECT dst, src FROM ce WHERE src <> dst)"
TERMINALS = "k AS MATERIALIZED (SELECT DISTINCT unnest(['C:' || o_custkey, 'S:' || l_suppkey, 'P:' || l_partkey]) AS node FROM note_lines)"
NET = "net AS MATERIALIZED (SELECT a.sty AS sty_src, rel AS srel, b.sty AS sty_dst, count(*) AS support FROM ce JOIN ct a ON a.concept_id = src JOIN ct b ON b.concept_id = dst GROUP BY ALL HAVING count(*) >= 20)"


def pruned(threshold: int = THRESHOLD) -> str:
    if threshold <= 0:
        return "kn AS MATERIALIZED (SELECT src AS node FROM ue UNION SELECT node FROM k), pe AS MATERIALIZED (SELECT * FROM ue)"
    return (
        f"kn AS MATERIALIZED (SELECT src AS node FROM ue WHERE dst IN (SELECT node FROM k) GROUP BY src HAVING count(*) >= {threshold} UNION SELECT node FROM k), "
        "pe AS MATERIALIZED (SELECT src, dst FROM ue WHERE src IN (SELECT node FROM kn) AND dst IN (SELECT node FROM kn))"
    )


def bfs(levels: int = LEVELS) -> str:
    """Unrolled levels: ``forest(node, parent, depth, root, path)``; one component besides single terminals."""
    out = ["lv0 AS MATERIALIZED (SELECT node, CAST(NULL AS VARCHAR) AS parent, 0 AS depth, node AS root, [node] AS path FROM (SELECT src AS node FROM pe WHERE src IN (SELECT node FROM k) GROUP BY src ORDER BY count(*) DESC, src LIMIT 1) UNION ALL SELECT node, NULL, 0, node, [node] FROM k WHERE node NOT IN (SELECT src FROM pe)), seen0 AS MATERIALIZED (SELECT node FROM lv0)"]
    for i in range(1, levels + 1):
        j = i - 1
        out.append(
            f"lv{i} AS MATERIALIZED (SELECT m.node, m.parent, {i} AS depth, p.root, list_append(p.path, m.node) AS path FROM (SELECT e.dst AS node, min(e.src) AS parent FROM lv{j} l JOIN pe e ON e.src = l.node WHERE e.dst NOT IN (SELECT node FROM seen{j}) GROUP BY 1) m JOIN lv{j} p ON p.node = m.parent), "
            f"seen{i} AS MATERIALIZED (SELECT node FROM seen{j} UNION ALL SELECT node FROM lv{i})"
        )
    return ", ".join(out) + ", forest AS MATERIALIZED (" + union([f"SELECT * FROM lv{i}" for i in range(levels + 1)]) + ")"


ALIGNED = (
    "al AS MATERIALIZED (SELECT DISTINCT sent_id, tok, concept_id FROM (SELECT sent_id, CAST(d AS INT) AS tok, 'C:' || o_custkey AS concept_id FROM note_lines WHERE kind IN (0, 2) "
    "UNION ALL SELECT sent_id, CAST(supp_at AS INT), 'S:' || l_suppkey FROM note_lines WHERE kind IN (0, 1, 3) UNION ALL SELECT sent_id, CAST(part_at + 1 AS INT), 'P:' || l_partkey FROM note_lines "
    "UNION ALL SELECT sent_id, CAST(next_at + 1 AS INT), 'P:' || next_part FROM note_lines WHERE kind = 3))"
)
TREES = (
    "tm AS MATERIALIZED (SELECT DISTINCT a.sent_id, f.root, a.concept_id, f.path FROM al a JOIN forest f ON f.node = a.concept_id), "
    "tk AS (SELECT sent_id, root, count(*) AS k FROM tm GROUP BY ALL), "
    "tu AS (SELECT sent_id, root, unnest(path) AS node, generate_subscripts(path, 1) - 1 AS depth, path FROM tm), "
    "tc AS (SELECT u.sent_id, u.root, node, min(depth) AS depth, count(*) AS c, min(CASE WHEN depth > 0 THEN path[depth] END) AS parent FROM tu u GROUP BY ALL), "
    "tl AS (SELECT c.sent_id, c.root, max(depth) AS lca FROM tc c JOIN tk USING (sent_id, root) WHERE c.c = tk.k GROUP BY ALL), "
    "st AS MATERIALIZED (SELECT c.sent_id, c.root, c.node, CASE WHEN depth > lca THEN parent END AS parent FROM tc c JOIN tl USING (sent_id, root) WHERE depth >= lca)"
)


def sentence_edges(types: bool = True, induce: str = "tree") -> str:
    if induce == "tree":
        steps = "SELECT sent_id, node AS x, parent AS y FROM st WHERE parent IS NOT NULL UNION ALL SELECT sent_id, parent, node FROM st WHERE parent IS NOT NULL"
    else:
        steps = "SELECT a.sent_id, a.node AS x, b.node AS y FROM st a JOIN st b ON a.sent_id = b.sent_id AND a.node <> b.node"
    parts = [
        f"SELECT DISTINCT sent_id, src, rel, dst FROM ({steps}) s JOIN ce ON ce.src = s.x AND ce.dst = s.y",
        "SELECT DISTINCT a.sent_id, 't:' || tok, 11, concept_id FROM al a JOIN st ON st.sent_id = a.sent_id AND st.node = a.concept_id",
    ]
    if types:
        parts.append("SELECT DISTINCT st.sent_id, node, 12, sty FROM st JOIN ct ON concept_id = node")
        parts.append("SELECT DISTINCT a.sent_id, sty_src, srel, sty_dst FROM (SELECT DISTINCT sent_id, sty FROM st JOIN ct ON concept_id = node) a JOIN net ON sty_src = a.sty JOIN (SELECT DISTINCT sent_id, sty FROM st JOIN ct ON concept_id = node) b ON b.sent_id = a.sent_id AND b.sty = sty_dst")
    return (
        f"s1 AS MATERIALIZED ({union(parts)}), se AS MATERIALIZED (SELECT sent_id, i, j, list_sort(list(DISTINCT rel)) AS rels FROM "
        "(SELECT sent_id, src AS i, rel, dst AS j FROM s1 UNION ALL SELECT sent_id, dst, rel, src FROM s1) WHERE i <> j GROUP BY sent_id, i, j)"
    )


def with_notes(*ctes: str) -> str:
    return "WITH " + ", ".join([notes.sql_cte(), *ctes]) + " "


TO_TREES = (EDGES, BOTH, TERMINALS, pruned(), bfs(), ALIGNED, TREES)
