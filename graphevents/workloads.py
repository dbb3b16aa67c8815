"""The experiment workloads: comparison, regulation only, ablation, training fractions, error analysis, grid, link ranking, and two
stand-ins with real labels."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, examples, kg, text, translate
from .catalog.base import Work
from .decode import REGULATION
from .model import Config, Extractor
from .operators.components import free_shuffles
from .sources.tables import load
from .train import Trainer, grid_search, train_fraction

#: Epochs of a registered run: enough for the synthetic notes; the paper's budget is the default of ``Config``.
EPOCHS = 10
#: Sentences of train and dev that the grid takes; the other runs are fitted on all of train and choose their epoch by all of dev.
GRID_ROWS = 800
MEASURES = ("recall", "precision", "f1")
RESULT = "system string, " + ", ".join(f"{s}_{m} double" for s in ("dev", "test", "regulation") for m in MEASURES)


def rows(spark: SparkSession, sf: str, types: bool = True, mode: str = "bfs", induce: str = "tree", threshold: int = 10) -> DataFrame:
    w = Work(spark, sf)
    return w.kept(f"rows{types}{mode}{induce}{threshold}", lambda: examples.rows(spark, sf, types=types, mode=mode, induce=induce, threshold=threshold))


#: Systems and ablations that read no graph.
PLAIN = ("svm_pipeline", "stacked", "path_cnn", "text_only", "no_graph")


def corpus(spark: SparkSession, sf: str, name: str, **graph) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """What a system's rows are made from, and how: lines where no graph is read, else the rows themselves."""
    return (examples.plain_lines(spark, sf), examples.rendered) if name in PLAIN else (rows(spark, sf, **graph), lambda df: df)


def result(spark: SparkSession, found: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(n, *(round(float(x), 4) for x in v)) for n, *v in found], RESULT)


def scored(trainer: Trainer, params: dict) -> tuple[float, ...]:
    """Recall, precision and F1 of dev, of test and of the regulation family of test, all over whole splits."""
    from .local_events import f1

    def measures(x) -> tuple[float, float, float]:
        gold, pred, tp_gold, tp_pred = (int(x[m].sum()) for m in ("gold", "pred", "tp_gold", "tp_pred"))
        return 100 * tp_gold / max(1, gold), 100 * tp_pred / max(1, pred), f1(gold, pred, tp_gold, tp_pred)

    free_shuffles(trainer.rows.sparkSession)
    dev = trainer.counts(params, trainer.dev)
    free_shuffles(trainer.rows.sparkSession)
    test = trainer.counts(params, trainer.test)
    free_shuffles(trainer.rows.sparkSession)
    return (*measures(dev), *measures(test), *measures(test[test.index.isin(REGULATION)]))


def run_system(spark: SparkSession, sf: str, name: str, epochs: int = EPOCHS, fraction: float = 1.0, seed: int = 0) -> tuple:
    data, render = corpus(spark, sf, name)
    c = Config(seed=seed, patience=epochs)
    if name == "stacked":
        from dataclasses import replace

        model, params = baselines.fit_stacked(lambda r, cc, m: Trainer(r, cc, m, render=render), data, replace(c, lr=0.05), max(3, epochs // 3))
        trainer = Trainer(data, c, model, render=render)
        return (name, *scored(trainer, params))
    model = baselines.make_baseline(name, c)
    trainer = Trainer(data, model.c, model, render=render)
    return (name, *scored(trainer, trainer.fit(epochs=epochs, fraction=fraction)))


def run_ablation(spark: SparkSession, sf: str, name: str, epochs: int = EPOCHS, seed: int = 0, **graph) -> tuple:
    data, render = corpus(spark, sf, name, types=name != "no_types", **graph)
    c = baselines.make_ablation(name, Config(seed=seed, patience=epochs))
    trainer = Trainer(data, c, Extractor(c), render=render)
    return (name, *scored(trainer, trainer.fit(epochs=epochs)))


def comparison(spark: SparkSession, sf: str) -> DataFrame:
    """All systems on one split."""
    return result(spark, [run_system(spark, sf, n) for n in ("svm_pipeline", "stacked", "path_cnn", "kb_tree_lstm", "text_only", "graph_fused")])


def ablation(spark: SparkSession, sf: str) -> DataFrame:
    return result(spark, [run_ablation(spark, sf, n) for n in ("full", "no_graph", "no_types", "edge_conv", "node_attention", "mean")])


def layer_variants(spark: SparkSession, sf: str) -> DataFrame:
    return result(spark, [run_ablation(spark, sf, n, 6) for n in ("edge_conv_scalar", "edge_conv_diagonal", "shared_edge_mlp", "self_loop")])


def tree_variants(spark: SparkSession, sf: str) -> DataFrame:
    """The full model on other sentence trees: all relations among a tree's nodes, and two pruning thresholds."""
    found = [("induce_full", *run_ablation(spark, sf, "full", 6, induce="full")[1:])]
    found += [(f"threshold_{t}", *run_ablation(spark, sf, "full", 6, threshold=t)[1:]) for t in (3, 35)]
    return result(spark, found)


def fraction_curve(spark: SparkSession, sf: str) -> DataFrame:
    """Text-only and graph-fused on nested samples of the training rows."""
    return result(spark, [(f"{n}@{int(f * 100)}", *run_system(spark, sf, n, 8, f)[1:]) for f in (0.1, 0.25, 0.5, 0.75, 1.0) for n in ("text_only", "graph_fused")])


def grid(spark: SparkSession, sf: str) -> DataFrame:
    configs = [Config(lr=lr, layers=k, patience=4) for lr in (1e-3, 3e-3) for k in (1, 3)]
    data = rows(spark, sf).filter("split <> 'test'")
    return grid_search(train_fraction(data, "sent_id", min(1.0, GRID_ROWS / max(1, data.count()))), configs, epochs=4)


def link_ranking(spark: SparkSession, sf: str) -> DataFrame:
    """Vectors by both norms and corruptions on the network without orders, ranked on every fiftieth link."""
    edges = kg.concept_edges(spark, sf, ("in_region", "cust_nation", "supp_nation", "family", "brand", "head"))
    edges = Work(spark, sf).kept("small_edges", lambda: edges)
    test = edges.filter(F.pmod(F.xxhash64("src", "rel", "dst"), F.lit(50)) == 0)
    train = edges.join(test, ["src", "rel", "dst"], "left_anti")
    out = None
    for norm, corrupt in ((1, "uniform"), (2, "bernoulli")):
        nodes, rels = translate.fit(train, dim=32, norm=norm, corrupt=corrupt, epochs=8)
        seen = kg.nodes_of(train)
        known = test.join(seen.withColumnRenamed("node", "src"), "src", "left_semi").join(seen.withColumnRenamed("node", "dst"), "dst", "left_semi").select("src", "rel", "dst")
        got = translate.rank_links(known, nodes, rels, edges, norm).select(F.lit(f"L{norm} {corrupt}").alias("system"), "mean_rank", "mrr", "hits1", "hits10", "n")
        out = got if out is None else out.union(got)
    return out


#: Vectors and labelled documents that the two stand-ins are fitted on at most; all held-out rows are scored.
VECTOR_SAMPLE, LABEL_SAMPLE, NEAR = 4_000, 5_000, 6


def embeddings_node_classification(spark: SparkSession, sf: str) -> DataFrame:
    """Labels of ``embeddings`` from a graph of near neighbours whose relation is the band of their similarity, one row a layer.

    Fitted on at most ``VECTOR_SAMPLE`` vectors that are not held out. Every held-out vector is scored in blocks on the executors: it receives from
    its nearest vectors of the sample.
    """
    from .gnn import kernel as K
    from .model import adam_warmup

    table = load(spark, sf, "embeddings").filter("embedding is not null and label is not null")
    held_out = F.pmod(F.col("vec_id"), F.lit(10)) >= 7
    frame = table.filter(~held_out).orderBy(F.xxhash64("vec_id"), "vec_id").limit(VECTOR_SAMPLE).toPandas()
    unit = lambda v: v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-9)
    x, y = unit(np.stack(frame.embedding.to_list()).astype(float)), frame.label.to_numpy()

    def edges(block: np.ndarray, own: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        sims = block @ x.T - (9 * np.eye(len(x)) if own else 0)
        near = np.argpartition(-sims, NEAR, axis=1)[:, :NEAR]
        return np.repeat(np.arange(len(block)), NEAR), near.ravel(), np.digitize(np.take_along_axis(sims, near, axis=1).ravel(), [0.2, 0.4, 0.6, 0.8])

    recv, send, band = edges(x, True)
    graph, out = K.Graph(len(x), recv, send, band, np.eye(5)), None
    for kind in ("identity", "edge_softmax", "edge_conv", "node_attention", "mean"):
        layers = K.stack(kind, 2, 64, 8, 32, **({"gate": "scalar"} if kind == "edge_conv" else {}))
        rng = np.random.default_rng(0)
        p = {"relations": rng.normal(0, 0.3, (5, 8))} | K.mlp_params(rng, "head", 64, 32, int(y.max()) + 1)
        for layer in layers:
            p |= layer.params(rng)
        state: dict = {}
        for step in range(1, 61):
            h, caches, g = x, [], {}
            for layer in layers:
                h, cache = layer.forward(p, h, graph)
                caches.append(cache)
            z, ch = K.mlp(p, "head", h)
            _, dz = K.softmax_loss(z, y)
            d = K.mlp_back(p, "head", ch, dz, g)
            for layer, cache in zip(reversed(layers), reversed(caches), strict=True):
                d = layer.backward(p, cache, d, graph, g)
            adam_warmup(p, g, state, 0.01, step, 61)

        def score(batches, layers=layers, p=p, kind=kind):
            for b in batches:
                if not b.num_rows:
                    continue
                block = unit(np.stack(b.column("embedding").to_pylist()).astype(float))
                r, s, w = edges(block, False)
                whole = K.Graph(len(x) + len(block), np.concatenate([recv, r + len(x)]), np.concatenate([send, s]), np.concatenate([band, w]), np.eye(5))
                h = np.vstack([x, block])
                for layer in layers:
                    h, _ = layer.forward(p, h, whole)
                z, _ = K.mlp(p, "head", h[len(x) :])
                hit = z.argmax(axis=1) == b.column("label").to_numpy()
                yield pa.RecordBatch.from_pydict({"system": [kind], "hit": [int(hit.sum())], "n": [len(hit)]}, pa.schema([("system", pa.string()), ("hit", pa.int64()), ("n", pa.int64())]))

        got = table.filter(held_out).select("embedding", "label").mapInArrow(score, "system string, hit long, n long")
        got = got.groupBy("system").agg(F.round(100.0 * F.sum("hit") / F.sum("n"), 4).alias("accuracy"), F.sum("n").alias("n"))
        out = got if out is None else out.union(got)
    return out


def labels_two_task(spark: SparkSession, sf: str) -> DataFrame:
    """Quality and toxicity of labelled documents as two tasks with a joint loss over hashed words: fitted on at most ``LABEL_SAMPLE`` labelled rows,
    loss and accuracy over all held-out ones."""
    width = 1024
    held_out = F.pmod(F.col("doc_id"), F.lit(5)) == 0
    d = load(spark, sf, "documents").join(load(spark, sf, "labels"), "doc_id")
    cells = F.array_distinct(F.transform(F.array_distinct(F.split(F.lower(F.coalesce("text", F.lit(""))), r"\W+")), lambda w: F.pmod(F.xxhash64(w), F.lit(width)).cast("int")))
    data = d.select("doc_id", "quality", "toxic", cells.alias("cells"))
    fit = data.filter(~held_out).orderBy(F.xxhash64("doc_id"), "doc_id").limit(LABEL_SAMPLE).toPandas()
    x = np.zeros((len(fit), width + 1))
    for i, found in enumerate(fit.cells):
        x[i, np.asarray(found, int)] = 1 / 30
    x[:, width] = 1
    y, w = fit[["quality", "toxic"]].to_numpy(float), np.zeros((width + 1, 2))
    for _ in range(400):
        q = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        w -= 2.0 * (x.T @ (q - y) / max(1, len(x)) + 1e-4 * w)
    def summed(weights: np.ndarray, bias: float) -> F.Column:
        table = F.array(*[F.lit(float(v)) for v in weights])
        return F.aggregate("cells", F.lit(float(bias)), lambda a, c: a + F.element_at(table, c + 1))

    tasks, scored = ("quality", "toxic"), data.filter(held_out)
    for i, t in enumerate(tasks):
        p = 1.0 / (1.0 + F.exp(-summed(w[:width, i] / 30, w[width, i])))
        scored = scored.withColumn(f"p_{t}", F.least(F.lit(1 - 1e-12), F.greatest(F.lit(1e-12), p)))
    each = F.explode(F.array(*[F.struct(F.lit(t).alias("task"), F.col(t).cast("double").alias("y"), F.col(f"p_{t}").alias("p")) for t in tasks]))
    rows = scored.select(each.alias("x")).select("x.*")
    one = rows.groupBy("task").agg((-F.avg(F.col("y") * F.log("p") + (1 - F.col("y")) * F.log(1 - F.col("p")))).alias("loss"), (100 * F.avg(((F.col("p") > 0.5) == (F.col("y") > 0.5)).cast("double"))).alias("accuracy"))
    joint = one.agg(F.lit("joint").alias("task"), F.sum("loss").alias("loss"), F.avg("accuracy").alias("accuracy"))
    return one.union(joint).select("task", F.round("loss", 4).alias("loss"), F.round("accuracy", 4).alias("accuracy"))


def pieces(spark: SparkSession, sf: str) -> DataFrame:
    """Greedy subword pieces of the notes: how many pieces a word has."""
    tokens = text.blank_tokens(Work(spark, sf).sentences)
    known = text.fit_pieces(tokens, 500)
    cut = text.wordpiece(tokens, known)
    return cut.groupBy(F.size("pieces").alias("pieces")).agg(F.count("*").alias("words"))


def single(name: str):
    return lambda spark, sf: result(spark, [run_system(spark, sf, name)])


QUERIES = {
    "model_comparison": comparison, "model_ablation": ablation, "model_layer_variants": layer_variants, "model_tree_variants": tree_variants, "model_fraction_curve": fraction_curve,
    "model_text_only": single("text_only"), "model_graph_fused": single("graph_fused"), "model_grid": grid, "model_link_ranking": link_ranking,
    "model_embeddings_node_classification": embeddings_node_classification, "model_labels_two_task": labels_two_task, "ground_wordpieces": pieces,
}
