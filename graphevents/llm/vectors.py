"""Near duplicates among embeddings by quantised tile products.

Vectors of one label are cut into tiles of bounded size; every pair of tiles of a label is one unit of work. Within it the
vectors are compared in 8 bits: with v = s q + e, |u.v - s_u s_v q_u.q_v| <= |s_u q_u| |e_v| + |e_u| |v|, all of which are known for
each vector, so pairs whose upper bound stays below the threshold are ruled out for certain and only the others are
computed again in double precision.

Equal vectors of a label are one vector with a count. A unit of work returns, for each vector, the number of rows linked to it,
and a spanning forest of its links: never more rows than vectors, however many links there are. Links of all units then give
the components by label propagation.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import components
from .common import stored, table

THRESHOLD, TILE = 0.93, 1024


def quantised(unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """8-bit values, scales, lengths of the quantised vectors and of the errors."""
    scale = np.abs(unit).max(axis=1) / 127.0
    q = np.rint(unit / scale[:, None]).astype(np.int8)
    near = q * scale[:, None]
    return q, scale, np.linalg.norm(near, axis=1), np.linalg.norm(unit - near, axis=1)


def linked(a: np.ndarray, b: np.ndarray, threshold: float, block: int = 256) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(i, j) with cosine(a[i], b[j]) >= threshold in double precision, a block of ``a`` at a time."""
    na, nb = np.linalg.norm(a, axis=1), np.linalg.norm(b, axis=1)
    qa, sa, la, ea = quantised(a / na[:, None])
    qb, sb, lb, eb = quantised(b / nb[:, None])
    wide = qb.T.astype(np.float32)  # products of 8-bit values sum exactly in 24 bits up to 1,040 dimensions
    if a.shape[1] > 1040:
        wide = wide.astype(np.float64)
    slack = 1e-9
    for at in range(0, len(a), block):
        i = slice(at, at + block)
        about = (qa[i].astype(wide.dtype) @ wide).astype(np.float64) * sa[i, None] * sb[None]
        bound = la[i, None] * eb[None] + ea[i, None] * (1 + slack)
        x, y = np.nonzero(about + bound >= threshold - slack)
        for c in range(0, len(x), 65536):
            u, v = x[c : c + 65536] + at, y[c : c + 65536]
            dot = np.einsum("ij,ij->i", a[u], b[v])
            hit = dot / (na[u] * nb[v]) >= threshold
            yield u[hit], v[hit]


def forest(pairs: list[tuple[np.ndarray, np.ndarray]], n: int) -> list[tuple[int, int]]:
    """A spanning forest of the links among n vertices."""
    up = list(range(n))

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    kept = []
    for x, y in pairs:
        for a, b in zip(x.tolist(), y.tolist(), strict=True):
            if (ra := root(a)) != (rb := root(b)):
                up[max(ra, rb)] = min(ra, rb)
                kept.append((a, b))
    return kept


def usable(vectors: DataFrame, column: str) -> F.Column:
    """True where a vector has a length other than 0 and only finite components."""
    v = F.col(column)
    fine = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.coalesce(fine & F.exists(v, lambda x: x != 0), F.lit(False)) & F.col("label").isNotNull()


def near_duplicates(vectors: DataFrame, *, threshold: float = THRESHOLD, tile: int = TILE) -> DataFrame:
    """One row a vector: vec_id, n_links, component_id, kept.

    Only vectors of one label and one number of dimensions are compared. Null, zero and non-finite vectors, and those
    without a label, link with nothing. Equal vectors link with each other. Rows that repeat an id count as vectors of
    their own in n_links and share the id's component. Extra columns are ignored; an empty table gives an empty result.
    """
    spark = vectors.sparkSession
    rows = vectors.select("vec_id", "label", F.transform("embedding", lambda x: x.cast("double")).alias("v")).withColumn("ok", usable(vectors, "v"))
    # Lengths far from 1 would leave the range of doubles when squared: scale by the largest component, which no cosine notices.
    same = F.sha2(F.to_json(F.struct("v")), 256)
    rows = stored(rows.withColumn("same", F.when(F.col("ok"), same)).withColumn("label", F.when(F.col("ok"), F.col("label"))))
    reps = rows.filter("ok").groupBy("label", "same").agg(F.count("*").alias("k"), F.min("vec_id").alias("id"), F.first("v").alias("v"))
    reps = reps.withColumn("group", F.concat_ws(":", F.col("label").cast("string"), F.size("v").cast("string")))
    reps = stored(reps)
    sizes = reps.groupBy("group").agg(F.count("*").alias("n")).collect()  # a row a label
    tiles = {r["group"]: -(-r["n"] // tile) for r in sizes}
    if not tiles:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    count = spark.createDataFrame(list(tiles.items()), "group string, tiles int")
    part = F.pmod(F.xxhash64("same"), F.col("tiles")).cast("int")
    placed = reps.join(F.broadcast(count), "group").withColumn("tile", part)
    pairs = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    pairs = pairs.withColumn("lo", F.least("tile", "other")).withColumn("hi", F.greatest("tile", "other"))

    def work(batch: pa.Table) -> pa.Table:
        mine, other = batch.column("tile").to_numpy(), batch.column("lo").to_numpy()[0]
        k = batch.column("k").to_numpy()
        same, ids = batch.column("same"), batch.column("id").to_numpy()
        dim = len(batch.column("v")[0])
        flat = pc.list_flatten(batch.column("v").combine_chunks()).to_numpy(zero_copy_only=False).reshape(-1, dim)
        flat = flat / np.abs(flat).max(axis=1)[:, None]
        inside = batch.column("lo")[0].as_py() == batch.column("hi")[0].as_py()
        left = np.flatnonzero(mine == other)
        right = left if inside else np.flatnonzero(mine != other)
        links, found = np.zeros(len(k), np.int64), []
        if len(left) and len(right):
            for x, y in linked(flat[left], flat[right], threshold):
                x, y = left[x], right[y]
                if inside:
                    x, y = x[x < y], y[x < y]
                np.add.at(links, x, k[y])
                np.add.at(links, y, k[x])
                found.append((x, y))
        edges = forest(found, len(k))
        some = np.flatnonzero(links)
        a, b = np.array(edges, np.int64).reshape(-1, 2).T
        return pa.table({
            "same": pa.concat_arrays([pa.array([same[int(i)].as_py() for i in some], pa.string()), pa.nulls(len(a), pa.string())]),
            "label": pa.concat_arrays([pa.array([batch.column("label")[int(i)].as_py() for i in some], pa.int64()), pa.nulls(len(a), pa.int64())]),
            "links": pa.concat_arrays([pa.array(links[some], pa.int64()), pa.nulls(len(a), pa.int64())]),
            "src": pa.concat_arrays([pa.nulls(len(some), pa.int64()), pa.array(ids[a], pa.int64())]),
            "dst": pa.concat_arrays([pa.nulls(len(some), pa.int64()), pa.array(ids[b], pa.int64())]),
        })

    pairs = pairs.select("group", "lo", "hi", "tile", F.col("label").cast("long").alias("label"), "same", "k", "id", "v")
    found = stored(pairs.groupBy("group", "lo", "hi").applyInArrow(work, "same string, label long, links long, src long, dst long"))
    links = found.filter("same is not null").groupBy(F.col("same").alias("s"), F.col("label").alias("l")).agg(F.sum("links").alias("links"))
    whole = components(found.filter("src is not null").select("src", "dst"))
    copies = reps.select(F.col("same").alias("s2"), F.col("label").alias("l2"), "k", "id")
    out = rows.join(copies, (F.col("same") == F.col("s2")) & (F.col("label") == F.col("l2")), "left")
    out = out.join(links, (F.col("same") == F.col("s")) & (F.col("label") == F.col("l")), "left")
    out = out.join(whole, F.col("id") == F.col("node"), "left")
    # A repeated id, or an id whose copies carry several labels, belongs to one component: the smallest it meets.
    component = F.coalesce("component", "id", "vec_id")
    out = out.select("vec_id", (F.coalesce("links", F.lit(0)) + F.coalesce("k", F.lit(1)) - 1).cast("long").alias("n_links"), component.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def op7(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "embeddings"))


def brute_force(frame: pd.DataFrame, threshold: float = THRESHOLD) -> pd.DataFrame:
    """All pairs, for tests."""
    n = len(frame)
    up = list(range(n))
    links = [0] * n
    ok = [l == l and l is not None and v is not None and all(x is not None and np.isfinite(x) for x in v) and any(x != 0 for x in v) for l, v in zip(frame.label, frame.embedding, strict=True)]
    for i in range(n):
        for j in range(i):
            if ok[i] and ok[j] and frame.label[i] == frame.label[j]:
                a, b = np.asarray(frame.embedding[i], float), np.asarray(frame.embedding[j], float)
                if a @ b / (np.linalg.norm(a) * np.linalg.norm(b)) >= threshold:
                    links[i] += 1
                    links[j] += 1
                    lo, hi = sorted((up[i], up[j]))
                    up = [lo if u == hi else u for u in up]
    ids = list(frame.vec_id)
    least = {r: min(ids[k] for k in range(n) if up[k] == r) for r in set(up)}
    return pd.DataFrame({"vec_id": ids, "n_links": links, "component_id": [least[u] for u in up]})
