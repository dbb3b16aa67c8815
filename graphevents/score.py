"""Matching predicted events with gold ones, and what follows from it."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .decode import one_a_row

GROUPS = {"Accept": "simple", "Hold": "simple", "Return": "simple", "Binding": "binding", "Negative": "regulation", "Positive": "regulation", "Regulation": "regulation"}


def group_of(etype) -> F.Column:
    return F.element_at(F.create_map(*[F.lit(x) for kv in GROUPS.items() for x in kv]), etype)


def flat_events(triggers: DataFrame, events: DataFrame) -> DataFrame:
    """Events with their trigger's span: sent_id, event_id, etype, level, tok_from, tok_to, theme, cause."""
    return events.join(triggers.select("sent_id", "trig_id", "tok_from", "tok_to"), ["sent_id", "trig_id"]).select("sent_id", "event_id", "etype", "level", "tok_from", "tok_to", "theme", "cause")


def span_matches(span: str = "approx") -> F.Column:
    """Predicted ``p_from, p_to`` against gold ``g_from, g_to``: equal, or inside the gold span widened by a word on either side."""
    if span == "strict":
        return (F.col("p_from") == F.col("g_from")) & (F.col("p_to") == F.col("g_to"))
    return (F.col("p_from") >= F.col("g_from") - 1) & (F.col("p_to") <= F.col("g_to") + 1)


def with_spans(rows: DataFrame, t: str, events: str, out: str) -> DataFrame:
    """``rows`` with ``out``, the events with the spans of their triggers."""
    e = f"named_struct('event_id', e.event_id, 'etype', e.etype, 'tok_from', x.tok_from, 'tok_to', x.tok_to, 'theme', e.theme, 'cause', e.cause)"
    return rows.withColumn(out, F.expr(f"flatten(transform({events}, e -> transform(filter({t}, x -> x.trig_id = e.trig_id), x -> {e})))"))


def by_sentence(gold: DataFrame, pred: DataFrame) -> DataFrame:
    """``sent_id, g, p``: a row a sentence with its gold and its predicted events."""
    side = lambda df, x: df.groupBy("sent_id").agg(F.collect_list(F.struct("event_id", "etype", "tok_from", "tok_to", "theme", "cause")).alias(x))
    return side(gold, "g").join(side(pred, "p"), "sent_id", "full_outer").select("sent_id", F.coalesce("g", F.array()).alias("g"), F.coalesce("p", F.array()).alias("p"))


def matched(rows: DataFrame, span: str = "approx", recursive: str = "approx", max_depth: int = 5) -> DataFrame:
    """``g, p`` -> also m, the matching events of each sentence as (g, p).

    Same type, matching triggers, same entity arguments, and event arguments that match in turn, level by level from the leaves. Under
    approximate recursion an event argument needs only its type, trigger and themes to match. All pairs are within a sentence, so they are
    made where its row is.
    """
    near = "y.tok_from = x.tok_from and y.tok_to = x.tok_to" if span == "strict" else "y.tok_from >= x.tok_from - 1 and y.tok_to <= x.tok_to + 1"
    pair = "named_struct('g', x.event_id, 'p', y.event_id, 'gt', x.theme, 'pt', y.theme, 'gc', x.cause, 'pc', y.cause)"
    entity = lambda c: f"(b.{c} is null or startswith(b.{c}, 'e'))"
    same_theme, same_cause = f"({entity('gt')} and b.gt = b.pt)", f"(b.gc <=> b.pc and {entity('gc')})"
    ids = lambda cond: f"array_distinct(transform(filter(_pairs, b -> {cond}), b -> named_struct('g', b.g, 'p', b.p)))"
    hit = lambda x: f"exists(_inner, i -> i.g = b.g{x} and i.p = b.p{x})"
    rows = rows.withColumn("_pairs", F.expr(f"flatten(transform(g, x -> transform(filter(p, y -> y.etype = x.etype and {near}), y -> {pair})))"))
    rows = rows.withColumn("_inner", F.expr(ids(same_theme if recursive == "approx" else f"{same_theme} and {same_cause}")))
    theme, cause = f"({same_theme} or {hit('t')})", f"({same_cause} or {hit('c')})"
    for _ in range(max_depth - 1):
        rows = rows.withColumn("_inner", F.expr(ids(theme if recursive == "approx" else f"{theme} and {cause}")))
    return rows.withColumn("m", F.expr(ids(f"{theme} and {cause}"))).drop("_pairs", "_inner")


def match_events(gold: DataFrame, pred: DataFrame, span: str = "approx", recursive: str = "approx", max_depth: int = 5) -> DataFrame:
    """``sent_id, gold_id, pred_id`` of matching events, as ``matched`` finds them."""
    got = matched(by_sentence(gold, pred), span, recursive, max_depth)
    return one_a_row(got, "m", "g", "p").select("sent_id", F.col("g").alias("gold_id"), F.col("p").alias("pred_id"))


def ratios(df: DataFrame) -> DataFrame:
    """recall, precision and f1 in percent from gold, pred, tp_gold, tp_pred; an empty denominator gives 0."""
    part = lambda a, b: F.when(F.col(b) > 0, 100.0 * F.col(a) / F.col(b)).otherwise(0.0)
    df = df.withColumn("recall", part("tp_gold", "gold")).withColumn("precision", part("tp_pred", "pred"))
    total = F.col("recall") + F.col("precision")
    return df.withColumn("f1", F.when(total > 0, 2 * F.col("recall") * F.col("precision") / total).otherwise(0.0))


def counts(rows: DataFrame) -> DataFrame:
    """``g, p, m`` of sentences -> ``etype, group, gold, pred, tp_gold, tp_pred`` a type."""
    one = lambda x, gold, pred: f"transform({x}, e -> named_struct('etype', e.etype, 'gold', {gold[0]}, 'pred', {pred[0]}, 'tp_gold', {gold[1]}, 'tp_pred', {pred[1]}))"
    hit = lambda x: f"if(exists(m, i -> i.{x} = e.event_id), 1L, 0L)"
    each = F.expr(f"concat({one('g', ('1L', hit('g')), ('0L', '0L'))}, {one('p', ('0L', '0L'), ('1L', hit('p')))})")
    got = rows.select(F.explode(each).alias("e")).groupBy("e.etype").agg(*[F.sum(f"e.{c}").alias(c) for c in ("gold", "pred", "tp_gold", "tp_pred")])
    return got.withColumn("group", group_of(F.col("etype")))


def evaluate(gold: DataFrame, pred: DataFrame, span: str = "approx", recursive: str = "approx") -> DataFrame:
    """``group, etype, gold, pred, tp_gold, tp_pred, recall, precision, f1``: by type, by group and for all (null where rolled up)."""
    return evaluate_rows(by_sentence(gold, pred), span, recursive)


def evaluate_rows(rows: DataFrame, span: str = "approx", recursive: str = "approx") -> DataFrame:
    """The same from ``g, p`` of sentences."""
    c = counts(matched(rows, span, recursive))
    sums = [F.sum(x).alias(x) for x in ("gold", "pred", "tp_gold", "tp_pred")]
    return ratios(c.rollup("group", "etype").agg(*sums))


def macro(by_type: DataFrame) -> DataFrame:
    return by_type.filter("etype is not null").agg(*[F.avg(x).alias(x) for x in ("recall", "precision", "f1")])


def trigger_scores(gold: DataFrame, pred: DataFrame, span: str = "approx") -> DataFrame:
    """Triggers alone: sent_id, trig_id, tok_from, tok_to, etype on both sides."""
    side = lambda df, x: df.select("sent_id", "etype", F.col("trig_id").alias(f"{x}_id"), F.col("tok_from").alias(f"{x}_from"), F.col("tok_to").alias(f"{x}_to"))
    hits = side(gold, "g").join(side(pred, "p"), ["sent_id", "etype"]).filter(span_matches(span))
    one = lambda df, what, name: df.agg(what.alias(name))
    parts = [one(gold, F.count("*"), "gold"), one(pred, F.count("*"), "pred"), one(hits, F.count_distinct("g_id"), "tp_gold"), one(hits, F.count_distinct("p_id"), "tp_pred")]
    return ratios(reduce(DataFrame.crossJoin, parts))  # four tables of one row


def role_scores(gold: DataFrame, pred: DataFrame) -> DataFrame:
    """Arguments alone: equal sentence, trigger, role and target."""
    keys = ["sent_id", "trig_id", "role", "kind", "ref"]
    g, p = gold.select(*keys).distinct().withColumn("g", F.lit(1)), pred.select(*keys).distinct().withColumn("p", F.lit(1))
    both = g.join(p, keys, "full_outer").agg(F.count("g").alias("gold"), F.count("p").alias("pred"), F.count_if(F.col("g").isNotNull() & F.col("p").isNotNull()).alias("tp_gold"))
    return ratios(both.withColumn("tp_pred", F.col("tp_gold")))


def compare(a: DataFrame, b: DataFrame) -> DataFrame:
    """``group, etype, f1_a, f1_b, delta`` of two evaluations."""
    x, y = (d.select(F.coalesce("group", F.lit("all")).alias("group"), F.coalesce("etype", F.lit("all")).alias("etype"), F.col("f1").alias(n)) for d, n in ((a, "f1_a"), (b, "f1_b")))
    return x.join(y, ["group", "etype"], "full_outer").na.fill({"f1_a": 0.0, "f1_b": 0.0}).withColumn("delta", F.col("f1_b") - F.col("f1_a"))


def confusion(gold: DataFrame, pred: DataFrame) -> DataFrame:
    """``gold_type, pred_type, n`` by token of single-token triggers; '-' where one side has none."""
    g = gold.select("sent_id", F.col("tok_to").alias("tok"), F.col("etype").alias("gold_type"))
    p = pred.select("sent_id", F.col("tok_to").alias("tok"), F.col("etype").alias("pred_type"))
    return g.join(p, ["sent_id", "tok"], "full_outer").select(F.coalesce("gold_type", F.lit("-")).alias("gold_type"), F.coalesce("pred_type", F.lit("-")).alias("pred_type")).groupBy("gold_type", "pred_type").agg(F.count("*").alias("n"))


def adjective_report(triggers: DataFrame, tokens: DataFrame, adjectives: tuple[str, ...], grounded: DataFrame) -> DataFrame:
    """``split, triggers, adjectives, grounded``: triggers that are adjectives, and those of them that have a concept."""
    t = triggers.join(tokens.select("sent_id", F.col("tok").alias("tok_to"), "form"), ["sent_id", "tok_to"])
    t = t.join(grounded.select("sent_id", F.col("tok").alias("tok_to")).distinct().withColumn("hit", F.lit(1)), ["sent_id", "tok_to"], "left")
    adj = F.col("form").isin(*adjectives)
    return t.groupBy("split").agg(F.count("*").alias("triggers"), F.count_if(adj).alias("adjectives"), F.count_if(adj & F.col("hit").isNotNull()).alias("grounded"))


def bootstrap_diff(gold: DataFrame, a: DataFrame, b: DataFrame, reps: int = 200, seed: int = 1) -> DataFrame:
    """``rep, f1_a, f1_b, diff``: sentences resampled by Poisson weights from a hash of (sentence, repetition), the same for both systems."""
    per = []
    for pred, name in ((a, "a"), (b, "b")):
        m = match_events(gold, pred)
        g = gold.groupBy("sent_id").agg(F.count("*").alias("gold")).join(m.groupBy("sent_id").agg(F.count_distinct("gold_id").alias("tg"), F.count_distinct("pred_id").alias("tp")), "sent_id", "left")
        p = pred.groupBy("sent_id").agg(F.count("*").alias("pred"))
        per.append(g.join(p, "sent_id", "full_outer").na.fill(0).select("sent_id", F.lit(name).alias("system"), "gold", "pred", "tg", "tp"))
    u = F.pmod(F.xxhash64("sent_id", "rep", F.lit(seed)), F.lit(1 << 30)) / float(1 << 30)
    weight = sum((F.when(u > c, 1).otherwise(0) for c in (0.367879, 0.735759, 0.919699, 0.981012, 0.99634, 0.999406)), F.lit(0))
    rows = per[0].union(per[1]).withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1)))).withColumn("w", weight)
    s = rows.groupBy("rep", "system").agg(*[F.sum(F.col(c) * F.col("w")).alias(c) for c in ("gold", "pred", "tg", "tp")])
    r, q = F.col("tg") / F.greatest("gold", F.lit(1)), F.col("tp") / F.greatest("pred", F.lit(1))
    s = s.withColumn("f1", F.when(r + q > 0, 200.0 * r * q / (r + q)).otherwise(0.0))
    return s.groupBy("rep").agg(F.max(F.when(F.col("system") == "a", F.col("f1"))).alias("f1_a"), F.max(F.when(F.col("system") == "b", F.col("f1"))).alias("f1_b")).withColumn("diff", F.col("f1_b") - F.col("f1_a"))


def ranked(df: DataFrame, key: str) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.orderBy(key)))
