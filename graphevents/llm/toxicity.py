"""Toxicity by a weighted finite-state grammar over clauses.

A clause's words become symbols (insult, threat, target, negation, report, other) with a weight. Transducers over symbols then
mark the insults and threats that a negation, a target or a reporting word reaches: each is a small machine whose state says for how
many more symbols its word reaches, and which adds a mark to the symbols it passes on. Their composition is one machine
that reads the clause from left to right; a second composition, with reaches of its own, reads it from right to left ("a moron, said
nobody"). A last one-state transducer turns a marked symbol into one of the patterns - aimed, plain, negated, reported, threat
at a target. Weights multiply along arcs. A text's score is a logistic function of the weights its clauses emit, never of
words alone.

Insult stems and their weights come from labelled rows: prefixes whose share among toxic texts exceeds that among others by a
likelihood-ratio test, the shortest prefix that tells as much. Pattern weights are fitted on stems learned from the other
half of the rows. Both are fitted on a bounded sample of labelled rows (``SAMPLE``); every whole text is scored.
"""

from __future__ import annotations

import functools
import math
import re
from collections import defaultdict
from collections.abc import Iterator
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices, table

#: Labelled rows the model is fitted on at most: those with the least hash of their id.
SAMPLE = 8_000
SHORTEST, LONGEST = 4, 12
# Closed word classes in English, French, German and Spanish.
THREATS = {"kill", "hurt", "destroy", "smash", "burn", "shoot", "stab", "tuer", "frapper", "brûler", "töten", "umbringen", "schlagen", "verbrennen", "matar", "golpear", "quemar"}
TARGETS = {"you", "your", "he", "she", "him", "they", "them", "these", "those", "people", "tu", "toi", "vous", "il", "ils", "elles", "du", "dich", "ihr", "euch", "sie", "tú", "ti", "usted", "ustedes", "ellos"}
NEGATIONS = {"not", "no", "never", "isn't", "aren't", "don't", "without", "ne", "pas", "jamais", "nicht", "kein", "keine", "nie", "nunca", "jamás", "tampoco"}
REPORTS = {"said", "says", "wrote", "called", "claimed", "quoted", "quote", "dit", "écrit", "appelé", "sagte", "schrieb", "nannte", "dijo", "escribió", "llamó"}
SEEDS = {"idiot": 3.0, "moron": 3.0, "stupid": 2.5, "scum": 3.0, "worthless": 2.5, "pathetic": 2.5, "disgusting": 2.0, "imbécile": 3.0, "salaud": 3.0, "dummkopf": 3.0, "arschloch": 3.0, "imbécil": 3.0, "estúpid": 2.5}
PATTERNS = ("aimed", "plain", "negated", "reported", "threat", "words_with_weight", "weight_a_hit")
TOKEN = re.compile(r"[^\W_]+(?:'[^\W_]+)?|[.!?;:,\n|\"]")
#: How many symbols a negation, a target or a reporting word reaches, to its right and to its left.
REACH = {"negation": 3, "target": 4, "report": 12}
REACH_BACK = {"negation": 3, "target": 4, "report": 3}
SYMBOLS = ("insult", "threat", "target", "negation", "report", "other")
MARKED = ("insult", "threat")
END = set(".!?;:\n|")


def symbol(word: str, stems: dict[str, float]) -> tuple[str, float]:
    """The first transducer: a word's symbol and weight; of insult stems the longest that the word begins with."""
    for n in range(min(len(word), LONGEST), SHORTEST - 1, -1):
        w = stems.get(word[:n])
        if w is not None:
            return "insult", w
    if word in THREATS:
        return "threat", 1.0
    return ("negation" if word in NEGATIONS else "target" if word in TARGETS else "report" if word in REPORTS else "other"), 0.0


class Transducer:
    """A deterministic weighted transducer: ``arcs[state, read] = (next state, written, weight)``; it starts in ``start``, and every state
    is final. It writes one symbol for each one read."""

    def __init__(self, start, arcs: dict) -> None:
        self.start, self.arcs = start, arcs

    def run(self, symbols: list) -> list[tuple]:
        """(written, weight) of each of (symbol, weight)."""
        state, out = self.start, []
        for symbol, weight in symbols:
            state, written, factor = self.arcs[state, symbol]
            out.append((written, weight * factor))
        return out


def composed(first: Transducer, second: Transducer) -> Transducer:
    """The transducer that does at once what ``second`` makes of what ``first`` writes; only states that can be reached."""
    start = (first.start, second.start)
    reads: dict = {}
    for state, read in first.arcs:
        reads.setdefault(state, []).append(read)
    arcs, todo, seen = {}, [start], {start}
    while todo:
        a, b = state = todo.pop()
        for read in reads[a]:
            to_a, middle, one = first.arcs[a, read]
            to_b, written, two = second.arcs[b, middle]
            arcs[state, read] = ((to_a, to_b), written, one * two)
            if (to_a, to_b) not in seen:
                seen.add((to_a, to_b))
                todo.append((to_a, to_b))
    return Transducer(start, arcs)


def reaching(word: str, reach: int, alphabet: list[tuple]) -> Transducer:
    """Marks insults and threats at most ``reach`` symbols after ``word`` with it. The state counts how far it still reaches."""
    arcs = {}
    for left in range(reach + 1):
        for base, marks in alphabet:
            hit = base in MARKED and left > 0
            arcs[left, (base, marks)] = (reach if base == word else max(0, left - 1), (base, marks | {word}) if hit else (base, marks), 1.0)
    return Transducer(0, arcs)


def alphabet_of(words: tuple[str, ...]) -> list[tuple]:
    """Symbols with any of the marks that ``words`` may have left on them."""
    sets = [frozenset(w for i, w in enumerate(words) if k >> i & 1) for k in range(1 << len(words))]
    return [(s, m) for s in SYMBOLS for m in (sets if s in MARKED else sets[:1])]


def pattern_of(base: str, marks: frozenset) -> str | None:
    if base == "threat":
        return "threat" if "target" in marks and not marks & {"negation", "report"} else None
    if base != "insult":
        return None
    return "reported" if "report" in marks else "negated" if "negation" in marks else "aimed" if "target" in marks else "plain"


@functools.lru_cache(maxsize=1)
def grammar() -> tuple[Transducer, Transducer]:
    """The machine that reads a clause from its left and the one that reads what that wrote from its right and writes patterns."""
    words = ("negation", "target", "report")
    alphabet = alphabet_of(words)
    forth = functools.reduce(composed, [reaching(w, REACH[w], alphabet) for w in words])
    back = functools.reduce(composed, [reaching(w, REACH_BACK[w], alphabet) for w in words])
    patterns = Transducer(0, {(0, x): (0, pattern_of(*x), 1.0) for x in alphabet})
    return forth, composed(back, patterns)


def clause_patterns(clause: list[str], stems: dict[str, float]) -> list[tuple[str, float]]:
    """(pattern, weight) of each insult and aimed threat of one clause."""
    forth, back = grammar()
    read = [((what, frozenset()), weight) for what, weight in (symbol(w, stems) for w in clause)]
    return [(pattern, weight) for pattern, weight in reversed(back.run(forth.run(read)[::-1])) if pattern]


def emitted(text: str, stems: dict[str, float], heads: set[str]) -> np.ndarray:
    """What all clauses of a text emit, as features. Clauses without an insult or threat emit nothing and are skipped."""
    out = dict.fromkeys(PATTERNS, 0.0)
    tokens = TOKEN.findall(text.lower())
    hits = [i for i, t in enumerate(tokens) if t[:SHORTEST] in heads or t in THREATS]
    done, words = -1, set()
    for i in hits:
        if i <= done:
            continue
        a = i
        while a > done + 1 and tokens[a - 1] not in END:
            a -= 1
        b = i + 1
        while b < len(tokens) and tokens[b] not in END:
            b += 1
        done = b
        clause = [t for t in tokens[a:b] if t not in (",", '"')]
        for pattern, weight in clause_patterns(clause, stems):
            out[pattern] += max(weight, 0.0) if pattern != "threat" else 1.0
        words.update(t for t in clause if t[:SHORTEST] in heads and symbol(t, stems)[0] == "insult")
    weights = [symbol(w, stems)[1] for w in words]
    out["words_with_weight"] = sum(weights)
    out["weight_a_hit"] = max(weights, default=0.0)
    v = np.array([out[p] for p in PATTERNS])
    return np.log1p(np.maximum(v, 0.0))


def learned_stems(texts: list[str], toxic: np.ndarray) -> dict[str, float]:
    """Prefixes that toxic texts have more often, with their log odds. Near copies (texts with the same least word hash) count once."""
    seen: dict[str, dict] = {}
    totals = [set(), set()]
    for text, y in zip(texts, toxic.tolist(), strict=True):
        words = {w for w in TOKEN.findall(text.lower()) if len(w) >= SHORTEST}
        group = min((crc32(w.encode()) for w in words), default=0)
        totals[y].add(group)
        for p in {w[:n] for w in words for n in range(SHORTEST, min(len(w), LONGEST) + 1)}:
            seen.setdefault(p, ({}, {}))[y][group] = 1
    n = [max(1, len(t)) for t in totals]
    scored = {}
    # A prefix that all its texts have in the same longer form gives way to the longer one.
    vague = {p[:-1] for p, (non, tox) in seen.items() if p[:-1] in seen and len(seen[p[:-1]][1]) == len(tox) and len(seen[p[:-1]][0]) == len(non)}
    for p, (non, tox) in seen.items():
        t, f = len(tox), len(non)
        if t < 3 or p in vague:
            continue
        rate = (t + f) / (n[0] + n[1])
        g = sum(2 * k * math.log(k / (m * rate)) for k, m in ((t, n[1]), (f, n[0])) if k)
        odds = math.log((t + 0.5) / (n[1] + 1)) - math.log((f + 0.5) / (n[0] + 1))
        if g >= 16 and odds >= 1.5:
            scored[p] = odds
    kept: dict[str, float] = dict(SEEDS)
    for p in sorted(scored, key=lambda p: (len(p), p)):
        shorter = [kept[p[:k]] for k in range(SHORTEST, len(p)) if p[:k] in kept]
        if not shorter or scored[p] > shorter[-1] + 0.7:
            kept[p] = scored[p]
    return kept


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 40) -> np.ndarray:
    """Weights (bias first) by Newton steps."""
    x = np.column_stack([np.ones(len(x)), x])
    w = np.zeros(x.shape[1])
    penalty = np.full(x.shape[1], ridge)
    penalty[0] = 1e-3
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x.T * (p * (1 - p) + 1e-9)) @ x + np.diag(penalty), x.T @ (y - p) - penalty * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def fitted(rows: list[tuple[int, str, int]]) -> tuple[dict[str, float], np.ndarray]:
    """(doc_id, text, toxic) -> stems and pattern weights. Without both classes, the fixed stems with weights that call
    any text with an aimed, plain or threatening clause toxic."""
    rows = sorted(rows)
    y = np.array([r[2] for r in rows], np.int64)
    if len(set(y.tolist())) < 2:
        return dict(SEEDS), np.array([-2.0, 2.0, 2.0, 0.2, 0.2, 3.0, 0.5, 0.5])
    texts = [r[1] for r in rows]
    # Texts that are near copies of each other are in the same half.
    half = np.array([min((crc32(w.encode()) for w in set(t.lower().split())), default=0) % 2 for t in texts])
    x = np.zeros((len(rows), len(PATTERNS)))
    for h in (0, 1):
        other = np.flatnonzero(half != h)
        stems = learned_stems([texts[i] for i in other], y[other])
        heads = {s[:SHORTEST] for s in stems}
        for i in np.flatnonzero(half == h):
            x[i] = emitted(texts[i], stems, heads)
    return learned_stems(texts, y), logistic(x, y)


def held_out(doc_id) -> F.Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(True))


def sample(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> list[tuple[int, str, int]]:
    """At most ``most`` labelled rows that are not held out. The labels are chosen first, so what is broadcast is bounded."""
    known = labels.filter("doc_id is not null and toxic in (0, 1)").groupBy(F.col("doc_id").alias("id")).agg(F.max("toxic").alias("toxic"))
    some = known.filter(~held_out(F.col("id"))).orderBy(F.xxhash64("id"), "id").limit(most)
    rows = docs.select("doc_id", "text").join(F.broadcast(some), F.col("doc_id") == F.col("id")).select("id", "text", "toxic")
    return [(r["id"], r["text"] or "", int(r["toxic"])) for r in rows.toLocalIterator()]


def scored(docs: DataFrame, model: tuple[dict[str, float], np.ndarray]) -> DataFrame:
    """doc_id, held_out, score, predicted of every row. Null text counts as empty and gets the score of a text without clauses; a null
    doc_id counts as held out. Repeated rows are scored each, alike. Extra columns are ignored."""
    stems, weights = model
    heads = {s[:SHORTEST] for s in stems}
    rows = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.coalesce(F.col("text"), F.lit("")).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, "text"):
            x = np.array([emitted(t, stems, heads) for t in b.column("text").to_pylist()])
            score = 1 / (1 + np.exp(-np.clip(weights[0] + x @ weights[1:], -30, 30)))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(score)], ["doc_id", "held_out", "score"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    out = rows.mapInArrow(run, f"doc_id {kind}, held_out boolean, score double")
    return out.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def op3(spark, sf_dir: str) -> DataFrame:
    """Scores of all ``documents``, learned from ``labels`` of rows that are not held out; odd rows as in ``scored``."""
    docs = table(spark, sf_dir, "documents")
    return scored(docs, fitted(sample(docs, table(spark, sf_dir, "labels"))))
