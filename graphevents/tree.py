"""Trees that connect concepts: pruning, breadth-first forests, two Steiner approximations, subtrees of sentences.

Edges are ``src, dst``; every function reads them in both directions. Loops are one job a level with a reliable checkpoint, end when
a level is empty, and carry only the frontier; what is visited is one table that grows by a level at a time.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .kg import SOURCES, concept_edges, neighbours_in
from .operators.components import checkpointed, components
from .sources import notes
from .sources.tables import load


def undirected(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").union(edges.select("dst", "src")).filter("src <> dst").distinct()


def prune(edges: DataFrame, terminals: DataFrame, threshold: int = 35) -> DataFrame:
    """Edges among kept nodes: terminals and nodes with at least ``threshold`` distinct terminal neighbours."""
    both = undirected(edges)
    keep = kept_nodes(both, terminals, threshold)
    return both.join(keep.withColumnRenamed("node", "src"), "src", "left_semi").join(keep.withColumnRenamed("node", "dst"), "dst", "left_semi")


def kept_nodes(edges: DataFrame, terminals: DataFrame, threshold: int) -> DataFrame:
    if threshold <= 0:
        return edges.select(F.col("src").alias("node")).union(edges.select("dst")).union(terminals).distinct()
    rich = neighbours_in(edges.select("src", F.lit(0).alias("rel"), "dst"), terminals).filter(F.col("n") >= threshold).select("node")
    return rich.union(terminals).distinct()


#: Codes of terminals that are sent to all executors at most, some 40 bytes each; more of them meet the tables by a shuffle.
SENT_CODES = 4_000_000


def kept_of_tables(spark, sf_dir: str, codes: DataFrame, threshold: int) -> DataFrame:
    """``kept_nodes`` of the whole network for a ``threshold`` of at least 1, from the keys of the given tables; ``codes`` are the terminals.

    The network is never made: a class of nodes takes the keys of its terminal neighbours from the tables that hold both, which meet by one
    shuffle on the node's own key. A node of a class that has terminals is counted only if it is none, since terminals stay anyway.
    """
    few = codes.limit(SENT_CODES + 1).count() <= SENT_CODES
    known = F.broadcast(codes) if few else codes
    out = codes.select(notes.name_of(F.col("code")).alias("node"))
    for prefix, pairs in beside(spark, sf_dir, known).items():
        rich = pairs.distinct().groupBy("k").agg(F.count("*").alias("n")).filter(F.col("n") >= threshold)
        out = out.union(rich.select(F.concat(F.lit(prefix), F.col("k").cast("string"))))
    return out


def beside(spark, sf_dir: str, known: DataFrame) -> dict[str, DataFrame]:
    """``k, code`` by the prefix of a class: its nodes that are no terminals, with each terminal beside them; rows may repeat. All rows of a key are in one partition."""
    sides: dict[str, dict[tuple[str, str], list]] = {}
    for _, table, a, pa, b, pb in SOURCES:
        for node, prefix, other, of in ((a, pa, b, pb), (b, pb, a, pa)):
            if of in notes.CODED:
                sides.setdefault(prefix, {}).setdefault((table, node), []).append(notes.code(of, F.col(other)))
    out = {}
    for prefix, tables in sides.items():
        rows = [load(spark, sf_dir, table).select(F.col(node).alias("k"), F.array(*near).alias("near")) for (table, node), near in tables.items()]
        rows = reduce(DataFrame.unionByName, rows).filter("k is not null")
        if prefix in notes.CODED:
            rows = rows.withColumn("code", notes.code(prefix, F.col("k"))).join(known, "code", "left_anti").select("k", "near")
        out[prefix] = rows.repartition("k").select("k", F.explode("near").alias("code")).join(known, "code", "left_semi")
    return out


def choose_roots(edges: DataFrame, terminals: DataFrame, given: str | None = None) -> DataFrame:
    """``node`` of the root of each component with a terminal: the one given, else the terminal with most neighbours, the least on ties."""
    parts = components(edges)
    degree = undirected(edges).groupBy(F.col("src").alias("node")).agg(F.count("*").alias("deg"))
    of_terminals = terminals.join(parts, "node", "left").join(degree, "node", "left").select("node", F.coalesce("component", "node").alias("component"), F.coalesce("deg", F.lit(0)).alias("deg"))
    first = F.when(F.col("node") == F.lit(given), F.lit(-1)).otherwise(F.lit(0))
    return of_terminals.groupBy("component").agg(F.min(F.struct(first.alias("g"), (-F.col("deg")).alias("d"), "node")).alias("m")).select(F.col("m.node").alias("node"))


def bfs_forest(edges: DataFrame, roots: DataFrame, max_rounds: int = 100, switch: float = 0.3) -> DataFrame:
    """``node, parent, depth, root, path`` (root first). A node's parent is the least node of the level before it.

    A level is made by pushing the frontier over its edges. Once the frontier is a large share of what is visited, the join turns
    round: edges of unvisited nodes look for the frontier, so edges between visited nodes are never shuffled again.
    """
    both = checkpointed(undirected(edges))
    level = checkpointed(roots.select("node", F.lit(None).cast("string").alias("parent"), F.lit(0).alias("depth"), F.col("node").alias("root"), F.array("node").alias("path")))
    levels, visited, total = [level], level.select("node"), level.count()
    for depth in range(1, max_rounds):
        size = level.count()
        out = both
        if size > switch * total:
            out = both.join(visited.withColumnRenamed("node", "dst"), "dst", "left_anti")
        front = level.select(F.col("node").alias("src"), "root", "path")
        step = out.join(front, "src").select("src", F.col("dst").alias("node"), "root", "path")
        step = step.join(visited, "node", "left_anti")
        best = step.groupBy("node").agg(F.min(F.struct("src", "root", "path")).alias("m"))
        level = checkpointed(best.select("node", F.col("m.src").alias("parent"), F.lit(depth).alias("depth"), F.col("m.root").alias("root"), F.concat("m.path", F.array("node")).alias("path")))
        if level.isEmpty():
            break
        levels.append(level)
        visited = checkpointed(visited.union(level.select("node")))
        total += size
    else:
        raise RuntimeError(f"not settled after {max_rounds} rounds: raise max_rounds")
    return reduce(DataFrame.union, levels)


def bfs_sql(spark, edges: DataFrame, root: str, max_depth: int = 4) -> DataFrame:
    """``node, depth`` as one recursive statement. It walks all paths, since visited nodes can't be taken out: toy graphs only."""
    undirected(edges).createOrReplaceTempView("bfs_sql_edges")
    return spark.sql(f"""
        WITH RECURSIVE walk(node, depth) AS (
            SELECT '{root}', 0 UNION ALL SELECT e.dst, w.depth + 1 FROM walk w JOIN bfs_sql_edges e ON e.src = w.node WHERE w.depth < {max_depth})
        SELECT node, min(depth) AS depth FROM walk GROUP BY node""")


def sentence_trees(mentions: DataFrame, forest: DataFrame) -> DataFrame:
    """``sent_id, root, node, parent``: the subtree that joins a sentence's concepts, one per component it touches.

    A node is in it exactly when a concept lies at or below it and it is not above the lowest common ancestor of them all: exploding
    root paths and counting gives both. ``parent`` is null at the top. One shuffle by sentence, no traversal.
    """
    paths = forest.select(F.col("node").alias("concept_id"), "root", "path")
    found = mentions.select("sent_id", "concept_id").distinct().join(paths, "concept_id")
    k = found.groupBy("sent_id", "root").agg(F.count("*").alias("k"))
    up = found.select("sent_id", "root", F.posexplode("path").alias("depth", "node"), F.expr("path").alias("path"))
    up = up.withColumn("parent", F.when(F.col("depth") > 0, F.element_at("path", F.when(F.col("depth") > 0, F.col("depth")).otherwise(1))))
    c = up.groupBy("sent_id", "root", "node").agg(F.count("*").alias("c"), F.first("depth").alias("depth"), F.first("parent").alias("parent"))
    c = c.join(k, ["sent_id", "root"])
    lca = F.max(F.when(F.col("c") == F.col("k"), F.col("depth"))).over(Window.partitionBy("sent_id", "root"))
    c = c.withColumn("lca", lca).filter(F.col("depth") >= F.col("lca"))
    return c.select("sent_id", "root", "node", F.when(F.col("depth") > F.col("lca"), F.col("parent")).alias("parent"))


def sentence_trees_dfs(mentions: DataFrame, forest: DataFrame) -> DataFrame:
    """The same in depth-first order: root paths sorted as arrays are in preorder, and the tree is what each path adds to the one before
    it, above which everything that all paths share is cut off."""
    paths = forest.select(F.col("node").alias("concept_id"), "root", "path")
    found = mentions.select("sent_id", "concept_id").distinct().join(paths, "concept_id")
    group = Window.partitionBy("sent_id", "root")
    order = group.orderBy("path")
    common = F.aggregate(F.sequence(F.lit(1), F.least(F.size("first"), F.size("final"))), F.lit(0), lambda n, i: F.when((n == i - 1) & (F.element_at("first", i) == F.element_at("final", i)), i).otherwise(n))
    got = found.withColumn("before", F.lag("path").over(order)).withColumn("first", F.min("path").over(group)).withColumn("final", F.max("path").over(group)).withColumn("top", common)
    new = F.array_except("path", F.coalesce("before", F.array().cast("array<string>")))
    rows = got.select("sent_id", "root", "top", "path", F.explode(F.array_union(new, F.slice("path", F.col("top"), 1))).alias("node"))
    rows = rows.withColumn("at", F.array_position("path", F.col("node")).cast("int")).filter(F.col("at") >= F.col("top"))
    return rows.select("sent_id", "root", "node", F.when(F.col("at") > F.col("top"), F.element_at("path", F.when(F.col("at") > 1, F.col("at") - 1).otherwise(1))).alias("parent")).distinct()


def sentence_trees_broadcast(mentions: DataFrame, forest: DataFrame, most: int = 4_000_000) -> DataFrame:
    """The same on the map side: parents and depths of the forest as two integer arrays, sent to all executors once. The forest's size is
    checked; sentences are gathered by one grouping and no path is ever shuffled."""
    rows = forest.select("node", "parent", "depth", "root").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError("the forest is too large to broadcast: use sentence_trees")
    number = {r["node"]: i for i, r in enumerate(rows)}
    parent = np.array([number.get(r["parent"], -1) for r in rows], np.int32)
    depth = np.array([r["depth"] for r in rows], np.int32)
    shared = mentions.sparkSession.sparkContext.broadcast((number, [r["node"] for r in rows], parent, depth, [r["root"] for r in rows]))

    def run(batches):
        number, names, parent, depth, roots = shared.value
        for batch in batches:
            out = ([], [], [], [])
            for sid, concepts in zip(batch.column("sent_id").to_pylist(), batch.column("concepts").to_pylist(), strict=True):
                by_root: dict = {}
                for c in concepts:
                    if c in number:
                        by_root.setdefault(roots[number[c]], []).append(number[c])
                for root, ends in by_root.items():
                    nodes, top = set(), ends[0]
                    for e in ends[1:]:
                        a, b = top, e
                        while a != b:
                            a, b = (int(parent[a]), b) if depth[a] >= depth[b] else (a, int(parent[b]))
                        top = a
                    for e in ends:
                        while e not in nodes:
                            nodes.add(e)
                            if e == top:
                                break
                            e = int(parent[e])
                    for n in nodes:
                        for column, v in zip(out, (sid, root, names[n], None if n == top else names[parent[n]]), strict=True):
                            column.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), *[pa.array(c, pa.string()) for c in out[1:]]], ["sent_id", "root", "node", "parent"])

    grouped = mentions.groupBy("sent_id").agg(F.collect_set("concept_id").alias("concepts"))
    return grouped.mapInArrow(run, "sent_id long, root string, node string, parent string")


def voronoi_cells(edges: DataFrame, terminals: DataFrame, max_rounds: int = 100) -> DataFrame:
    """``node, owner, dist, parent``: the nearest terminal (the least on ties) and the way to it."""
    level = checkpointed(terminals.select("node", F.col("node").alias("owner"), F.lit(0).alias("dist"), F.lit(None).cast("string").alias("parent")))
    return reduce(DataFrame.union, spread(checkpointed(undirected(edges)), level, 1, max_rounds))


def spread(both: DataFrame, level: DataFrame, first: int, max_rounds: int = 100) -> list[DataFrame]:
    """``level`` and the levels of cells after it, from the distance ``first`` on."""
    levels, visited = [level], level.select("node")
    for dist in range(first, max_rounds):
        step = both.join(level.select(F.col("node").alias("src"), "owner"), "src").select(F.col("dst").alias("node"), "owner", "src").join(visited, "node", "left_anti")
        best = step.groupBy("node").agg(F.min(F.struct("owner", "src")).alias("m"))
        level = checkpointed(best.select("node", F.col("m.owner").alias("owner"), F.lit(dist).alias("dist"), F.col("m.src").alias("parent")))
        if level.isEmpty():
            break
        levels.append(level)
        visited = checkpointed(visited.union(level.select("node")))
    else:
        raise RuntimeError(f"not settled after {max_rounds} rounds: raise max_rounds")
    return levels


def cells_of_tables(spark, sf_dir: str, codes: DataFrame) -> DataFrame:
    """``node, owner, dist`` of ``voronoi_cells`` over the whole network, from the keys of the given tables; ``codes`` are the terminals.

    What is beside a terminal finds its owner by one shuffle on its own key. Edges with a terminal lead nowhere else, so the later levels walk
    only those without one.
    """
    known = F.broadcast(codes) if codes.limit(SENT_CODES + 1).count() <= SENT_CODES else codes
    name = notes.name_of(F.col("code"))
    first = [p.groupBy("k").agg(F.min(name).alias("owner")).select(F.concat(F.lit(prefix), F.col("k").cast("string")).alias("node"), "owner") for prefix, p in beside(spark, sf_dir, known).items()]
    first = reduce(DataFrame.union, first)
    rest = []
    for relation, table, a, pa, b, pb in SOURCES:
        rows = load(spark, sf_dir, table).select(F.col(a).alias("a"), F.col(b).alias("b")).filter("a is not null and b is not null")
        for side, prefix in (("a", pa), ("b", pb)):
            if prefix in notes.CODED:
                rows = rows.withColumn("code", notes.code(prefix, F.col(side))).join(known, "code", "left_anti").select("a", "b")
        rest.append(rows.select(F.concat(F.lit(pa), F.col("a").cast("string")).alias("src"), F.concat(F.lit(pb), F.col("b").cast("string")).alias("dst")))
    rest.append(concept_edges(spark, sf_dir, ("head",)).select("src", "dst"))
    both = checkpointed(undirected(reduce(DataFrame.union, rest)))
    front = checkpointed(first.join(both.select(F.col("src").alias("node")).distinct(), "node", "left_semi").select("node", "owner", F.lit(1).alias("dist"), F.lit(None).cast("string").alias("parent")))
    out = codes.select(name.alias("node"), name.alias("owner"), F.lit(0).alias("dist")).union(first.select("node", "owner", F.lit(1)))
    return reduce(DataFrame.union, [x.select("node", "owner", "dist") for x in spread(both, front, 2)[1:]], out)


def voronoi_links(edges: DataFrame, cells: DataFrame) -> DataFrame:
    """``a, b, length, u, v``: for two owners whose cells touch, the shortest way over one boundary edge (u, v)."""
    side = lambda x, o: cells.select(F.col("node").alias(x), F.col("owner").alias(o), F.col("dist").alias(f"d{x}"))
    cross = undirected(edges).select(F.col("src").alias("u"), F.col("dst").alias("v")).join(side("u", "a"), "u").join(side("v", "b"), "v").filter("a < b")
    best = cross.groupBy("a", "b").agg(F.min(F.struct((F.col("du") + F.col("dv") + 1).alias("length"), "u", "v")).alias("m"))
    return best.select("a", "b", "m.length", "m.u", "m.v")


def spanning_forest(links: DataFrame, max_rounds: int = 40) -> DataFrame:
    """The minimum spanning forest of ``a, b, length, u, v`` by Boruvka rounds: every component takes its least link."""
    links = checkpointed(links)
    label = links.select(F.explode(F.array("a", "b")).alias("node")).distinct().withColumn("component", F.col("node"))
    chosen = None
    for _ in range(max_rounds):
        la, lb = label.select(F.col("node").alias("a"), F.col("component").alias("ca")), label.select(F.col("node").alias("b"), F.col("component").alias("cb"))
        open_ = links.join(la, "a").join(lb, "b").filter("ca <> cb")
        each = open_.select(F.explode(F.array("ca", "cb")).alias("c"), F.struct("length", "a", "b", "u", "v").alias("x"))
        new = checkpointed(each.groupBy("c").agg(F.min("x").alias("x")).select("x.*").distinct())
        if new.isEmpty():
            break
        chosen = new if chosen is None else checkpointed(chosen.union(new).distinct())
        parts = components(chosen.select(F.col("a").alias("src"), F.col("b").alias("dst")))
        label = checkpointed(label.select("node").join(parts, "node", "left").select("node", F.coalesce("component", "node").alias("component")))
    else:
        raise RuntimeError(f"not settled after {max_rounds} rounds: raise max_rounds")
    return links.select("length", "a", "b", "u", "v").limit(0) if chosen is None else chosen


def voronoi_tree(edges: DataFrame, terminals: DataFrame) -> DataFrame:
    """``u, v``: edges of a tree over the terminals at most twice as long as the shortest one. Each chosen link is expanded over the two
    ways to its owners; ends that are no terminals are cut off to a fixpoint."""
    cells = checkpointed(voronoi_cells(edges, terminals))
    links = spanning_forest(voronoi_links(edges, cells))
    used = links.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
    front = links.select(F.explode(F.array("u", "v")).alias("node")).distinct()
    way = cells.filter("parent is not null").select("node", "parent")
    while True:
        step = checkpointed(front.join(way, "node"))
        if step.isEmpty():
            break
        used = used.union(step.select(F.least("node", "parent").alias("u"), F.greatest("node", "parent").alias("v")))
        front = step.select(F.col("parent").alias("node")).distinct()
    return trim(checkpointed(used.distinct()), terminals)


def trim(tree: DataFrame, terminals: DataFrame) -> DataFrame:
    """Without ends that are no terminals."""
    while True:
        ends = tree.select(F.explode(F.array("u", "v")).alias("node")).groupBy("node").count().filter("count = 1").select("node").join(terminals, "node", "left_anti")
        ends = checkpointed(ends)
        if ends.isEmpty():
            return tree
        tree = checkpointed(tree.join(ends.withColumnRenamed("node", "u"), "u", "left_anti").join(ends.withColumnRenamed("node", "v"), "v", "left_anti").select("u", "v"))


def closure_tree(edges: DataFrame, terminals: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``a, b, length``: the spanning tree of the exact distances between few terminals: one search a terminal, as rows (source, node)."""
    both = checkpointed(undirected(edges))
    level = checkpointed(terminals.select(F.col("node").alias("s"), "node"))
    seen, levels = level, [level.withColumn("d", F.lit(0))]
    for d in range(1, max_rounds):
        level = checkpointed(level.join(both, F.col("node") == F.col("src")).select("s", F.col("dst").alias("node")).distinct().join(seen, ["s", "node"], "left_anti"))
        if level.isEmpty():
            break
        seen = checkpointed(seen.union(level))
        levels.append(level.withColumn("d", F.lit(d)))
    else:
        raise RuntimeError(f"not settled after {max_rounds} rounds: raise max_rounds")
    reach = reduce(DataFrame.union, levels)
    pairs = reach.join(terminals, "node").filter("s < node").select(F.col("s").alias("a"), F.col("node").alias("b"), F.col("d").alias("length"), F.col("s").alias("u"), F.col("node").alias("v"))
    return spanning_forest(pairs).select("a", "b", "length")


def exact_steiner(edges: list[tuple], terminals: list) -> int:
    """Edges of the shortest tree over at most ten terminals, by a table over subsets. For tests and small cases."""
    nodes = sorted({x for e in edges for x in e} | set(terminals))
    index = {v: i for i, v in enumerate(nodes)}
    n, far = len(nodes), 1 << 20
    near = [[] for _ in nodes]
    for a, b in edges:
        near[index[a]].append(index[b])
        near[index[b]].append(index[a])

    def spread(cost: list[int]) -> list[int]:
        buckets = sorted(range(n), key=lambda v: cost[v])
        queue = [v for v in buckets if cost[v] < far]
        while queue:
            queue.sort(key=lambda v: cost[v])
            v = queue.pop(0)
            for w in near[v]:
                if cost[v] + 1 < cost[w]:
                    cost[w] = cost[v] + 1
                    queue.append(w)
        return cost

    k = len(terminals)
    best = {1 << i: spread([0 if v == index[t] else far for v in range(n)]) for i, t in enumerate(terminals)}
    for mask in range(1, 1 << k):
        if mask in best:
            continue
        cost, sub = [far] * n, (mask - 1) & mask
        while sub:
            cost = [min(c, x + y) for c, x, y in zip(cost, best[sub], best[mask ^ sub], strict=True)]
            sub = (sub - 1) & mask
        best[mask] = spread(cost)
    return min(best[(1 << k) - 1])


def tree_cost(trees: DataFrame) -> DataFrame:
    """``sent_id, nodes, edges`` of the sentences' trees."""
    return trees.groupBy("sent_id").agg(F.count("*").alias("nodes"), F.count("parent").alias("edges"))
