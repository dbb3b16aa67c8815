"""Quality rules with risk-controlled cutoffs.

Each rule is a number per document that is larger for worse text. For every stratum (language) and rule a cutoff is
chosen on labelled documents: going from the mildest cutoff to sharper ones, a cutoff is certified while the exact
binomial upper bound on the share of good documents it rejects stays at or below ``risk``. Testing in that fixed order
needs no correction along one rule; across rules and strata the error chance is divided by their number (Bonferroni), so
with chance 1 - error no certified rule rejects more than its allowed share of the good documents of its stratum. Among
certified cutoffs the one that rejects most labelled bad documents is used, the mildest on ties; a rule without a
certified cutoff that rejects any bad document is off in that stratum.

Scale: the counts are one pass of the features over the documents, a join of six small columns with the labels and an
aggregation to strata x rules x bins rows, which is all that reaches the driver.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import document, slices, stored, table, texts_of, with_text

SYMBOLS = "#*$%&|<>"
BLANKS = " \t\n\x0b\x0c\r"
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: Each rule: its value in SQL over the counts. The share of odd characters, of repeated lines a hundred words, of repeated words.
RULES = {
    "symbols": "n_symbols / greatest(word_chars, 1)",
    "dup_lines": "100 * n_dup_lines / greatest(n_words, 1)",
    "repeats": "n_repeat_words / greatest(n_words, 1)",
    "shouting": "n_shout / greatest(n_words, 1)",
}
#: Cutoffs of every rule, mildest first.
GRID = tuple(round(2.0 ** (-k / 4), 6) for k in range(0, 41))
RISK, ERROR = 0.02, 0.05


def text_counts(raw: bytes) -> tuple[int, ...]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, words in capitals."""
    text = raw.decode("utf-8", "replace")
    words = raw.split()
    n = len(words)
    chars = len(text) - sum(map(text.count, BLANKS))
    symbols = sum(map(text.count, SYMBOLS))
    lines = [line for line in text.split("\n") if line.strip(BLANKS)]
    dup = len(lines) - len(set(lines))
    repeat = 0
    if n >= 6:
        windows = list(zip(words, words[1:], words[2:], words[3:], words[4:], strict=False))
        often = Counter(windows)
        if len(often) < len(windows):
            last = -1  # words before this place are counted
            for i, w in enumerate(windows):
                if often[w] > 1:
                    repeat += i + 5 - max(i, last)
                    last = i + 5
    return n, chars, symbols, dup, repeat, sum(map(bytes.isupper, words))


def counted(docs: DataFrame, keep: list, whole: bool = False) -> DataFrame:
    """``keep`` beside the counts of every whole text; null text counts as empty. ``whole``: ``keep`` begins with ``document(docs)``."""
    rows, place = with_text(docs, keep, whole)
    names = (*COUNTS, "n_shout")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, place):
            got = list(zip(*[text_counts(t or b"") for t in texts_of(b, place).cast(pa.binary()).to_pylist()], strict=True))
            yield pa.RecordBatch.from_arrays([b.column("row"), *[pa.array(g, pa.int64()) for g in got]], ["row", *names])

    schema = f"row {rows.schema['row'].dataType.simpleString()}, " + ", ".join(f"{c} long" for c in names)
    return rows.mapInArrow(run, schema).select("row.*", *names)


def binomial_tail(k: int, n: int, p: float) -> float:
    """The chance of at most k successes in n."""
    logs = [math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(p) + (n - i) * math.log1p(-p) for i in range(k + 1)]
    top = max(logs)
    return min(1.0, math.exp(top) * sum(math.exp(x - top) for x in logs))


def certified(rejected: int, n: int, risk: float, error: float) -> bool:
    """Whether the exact upper bound, at confidence 1 - error, of the rejected share is at most ``risk``."""
    return n > 0 and rejected < risk * n and binomial_tail(rejected, n, risk) <= error


def choose(rows: list[tuple], *, risk: float = RISK, error: float = ERROR) -> dict:
    """``(stratum, rule, bin, good, count)`` -> {(stratum, rule): cutoff}. ``bin`` b holds values in [GRID[b], GRID[b - 1])."""
    strata = {r[0] for r in rows}
    each = error / max(1, len(strata) * len(RULES))
    cutoffs = {}
    for s in strata:
        for rule in RULES:
            mine = [r for r in rows if r[0] == s and r[1] == rule]
            n = sum(r[4] for r in mine if r[3] == 1)
            good = bad = best = 0
            for b, cutoff in enumerate(GRID):
                good += sum(r[4] for r in mine if r[2] == b and r[3] == 1)
                bad += sum(r[4] for r in mine if r[2] == b and r[3] == 0)
                if not certified(good, n, risk, each):
                    break
                if bad > best:
                    best, cutoffs[s, rule] = bad, cutoff
    return cutoffs


def fitted(counts: DataFrame, labels: DataFrame, **options) -> dict:
    """Cutoffs from the counts (with ``doc_id`` and ``stratum``) of the documents that ``labels`` has a quality for. Documents
    that the base conditions reject anyway tell nothing about the rules and are left out."""
    known = labels.select(F.col("doc_id").alias("id"), F.col("quality").alias("good")).filter("good in (0, 1)").distinct()
    pairs = counts.filter(~base_failed()).join(known, F.col("doc_id") == F.col("id"))
    bin_of = lambda v: F.aggregate(F.array(*[F.lit(g) for g in GRID]), F.lit(0), lambda n, g: n + F.when(v < g, 1).otherwise(0))
    each = F.explode(F.array(*[F.struct(F.lit(r).alias("rule"), bin_of(F.expr(e)).alias("bin")) for r, e in RULES.items()]))
    table_ = pairs.select("stratum", "good", each.alias("x")).groupBy("stratum", "x.rule", "x.bin", "good").count()
    return choose([(r["stratum"], r["rule"], r["bin"], r["good"], r["count"]) for r in table_.collect()], **options)


def base_failed() -> F.Column:
    return F.expr("n_words < 10 or 100 * n_repeat_words > 20 * n_words")


def verdict(cutoffs: dict, stratum) -> F.Column:
    """True where no rule of the row's stratum rejects and the base conditions hold."""
    bad = base_failed()
    for (s, rule), cutoff in sorted(cutoffs.items(), key=str):
        bad = bad | (stratum.eqNullSafe(F.lit(s)) & (F.expr(RULES[rule]) >= cutoff))
    return ~bad


def judge(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """One row a document: doc_id, the counts, base_failed, kept.

    Null text is empty: no words, base_failed. Null doc_id never meets a label. Repeated rows and ids are judged each by their
    own text. Labels outside 0 and 1 are not used; without labels only the base conditions reject. Extra columns are ignored.
    """
    counts = stored(counted(docs, [F.col("doc_id").alias("doc_id"), F.col("lang").alias("stratum")]))
    cutoffs = fitted(counts, labels, **options)
    return counts.select("doc_id", *COUNTS, base_failed().alias("base_failed"), verdict(cutoffs, F.col("stratum")).alias("kept"))


def kept_documents(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` that pass, unchanged. The text is read twice and never shuffled."""
    counts = stored(counted(docs, [F.col("doc_id").alias("doc_id"), F.col("lang").alias("stratum")]))
    cutoffs = fitted(counts, labels, **options)
    rows = counted(docs, [document(docs), F.col("lang").alias("stratum")], whole=True)
    return rows.filter(verdict(cutoffs, F.col("stratum"))).select("document.*")


def op6(spark, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
