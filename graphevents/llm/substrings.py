"""Removing long repeated passages by recompression.

Word sequences are rewritten in rounds. A round gives every neighbouring pair (left, right) of symbols a new symbol, where a hash
bit of each symbol says whether it may be a left or a right part; the name of the new symbol is a hash of the names of its
parts, so all tasks on all machines give equal pairs the equal name and no table of names has to be exchanged. Which symbols
come out in the inside of a passage depends on the passage alone: each symbol carries the stretch of words that decided it, and
a symbol whose stretch lies inside a window is found in every other occurrence of that window, at the same place.

Every window of ``width`` words is represented by one such symbol (the longest, then the least in hash order). Symbols that
are found once cannot be in a repeated window: that settles nearly all of a corpus with one count per symbol, about a
fourteenth of the words. Occurrences of shared symbols are compared in larger units first - the same whole surroundings found
twice means all windows are repeated; four neighbouring windows whose common words are found once are not - and only what
is left is compared window by window, with 128-bit names.
Windows in which nothing is decided from inside (long runs of a period) are named directly.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import bucketed, free_shuffles, mixed, slices, stored, table, word_hashes

WIDTH = 35
#: Rounds: a symbol spans at most 2^4 words and is decided by at most as many on either side, so 35 words hold one.
ROUNDS = 4
#: A name with fewer rows than this is never treated as a hot one.
HOT_ROWS = 10_000


def recompressed(names: np.ndarray, doc: np.ndarray, rounds: int) -> tuple[np.ndarray, ...]:
    """Symbols after ``rounds`` of pair naming over many documents at once: name, first word, end word, first and end of
    the deciding stretch, document."""
    n = len(names)
    begin, end = np.arange(n), np.arange(1, n + 1)
    low, high = begin.copy(), end.copy()
    for r in range(rounds):
        if len(names) < 2:
            break
        side = (mixed(names + np.uint64(0xA5A5 * (r + 1))) & np.uint64(1)).astype(bool)  # True: may be a left part
        near = doc[1:] == doc[:-1]
        pair = side[:-1] & ~side[1:] & near
        # The first and last symbol of a document, and of any window, depend on what may stand outside: a left part on its right
        # neighbour, a right part on its left one.
        right_high = np.concatenate([np.where(near, high[1:], high[:-1] + 1), high[-1:] + 1])
        left_low = np.concatenate([low[:1] - 1, np.where(near, low[:-1], low[1:] - 1)])
        high2 = np.where(side, right_high, high)
        low2 = np.where(side, low, left_low)
        tail = np.concatenate([[False], pair])  # right parts of pairs
        head = np.concatenate([pair, [False]])
        at = np.flatnonzero(head)
        joined = mixed(names[at] * np.uint64(0x9E3779B97F4A7C15) + mixed(names[at + 1] ^ np.uint64(r + 77)))
        names, end, low, high = names.copy(), end.copy(), low2, high2
        names[at], end[at] = joined, end[at + 1]
        low[at], high[at] = np.minimum(low2[at], low2[at + 1]), np.maximum(high2[at], high2[at + 1])
        keep = ~tail
        names, begin, end, low, high, doc = names[keep], begin[keep], end[keep], low[keep], high[keep], doc[keep]
    return names, begin, end, low, high, doc


def prefix_names(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Prefix sums from which any stretch's name follows, and the inverse powers for it."""
    base = 0xD1342543DE82EF95
    n = len(hashes) + 1
    up, down = np.full(n, base, np.uint64), np.full(n, pow(base, -1, 1 << 64), np.uint64)
    up[0] = down[0] = 1
    up, down = np.multiply.accumulate(up), np.multiply.accumulate(down)
    return np.concatenate([np.zeros(1, np.uint64), np.cumsum(hashes * up[: n - 1])]), down


def stretch_names(prefix: tuple[np.ndarray, np.ndarray], a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return mixed((prefix[0][b] - prefix[0][a]) * prefix[1][a] + (b - a).astype(np.uint64))


def anchored(hashes: np.ndarray, offsets: np.ndarray, width: int) -> tuple[np.ndarray, ...]:
    """Runs of windows with one representative: document, first window, number of windows, name of the representative,
    name of all the words that these windows cover, words from the first window to the stretch that decides the representative,
    words of that stretch. Places count words from the start of all the documents."""
    sizes = np.diff(offsets)
    windows_of = np.maximum(sizes - width + 1, 0)
    total = int(windows_of.sum())
    if not total:
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),) * 2 + (np.zeros(0, np.int64),) * 2
    doc_of = np.repeat(np.arange(len(sizes)), windows_of)
    first_window = np.concatenate([[0], np.cumsum(windows_of)])[:-1]
    start = offsets[:-1][doc_of] + np.arange(total) - first_window[doc_of]
    names, begin, end, low, high, _ = recompressed(hashes, np.repeat(np.arange(len(sizes)), sizes), ROUNDS)
    lo, hi = np.searchsorted(low, start, "left"), np.searchsorted(high, start + width, "right")
    # Longest first, then least hash: one number that is the smaller the better.
    span = np.minimum(end - begin, 255).astype(np.uint64)
    score = ((np.uint64(255) - span) << np.uint64(56)) | (mixed(names) >> np.uint64(8))
    levels = [np.arange(len(score))]
    while 1 << len(levels) <= 64 and 1 << (len(levels) - 1) < len(score):
        step, best = 1 << (len(levels) - 1), levels[-1]
        other = np.concatenate([best[step:], np.full(step, len(score) - 1)])
        levels.append(np.where(score[best] <= score[other], best, other))
    count = np.maximum(hi - lo, 0)
    power = np.frexp(np.maximum(count, 1))[1] - 1
    power = np.minimum(power, len(levels) - 1)
    stack = np.stack(levels)
    safe = np.minimum(lo, len(score) - 1)
    one, two = stack[power, safe], stack[power, np.maximum(hi - (1 << power), 0)]
    pick = np.where(score[one] <= score[two], one, two)
    pick = np.where(count > 0, pick, -1 - np.arange(total))  # none: a run of its own
    new = np.concatenate([[True], (pick[1:] != pick[:-1]) | (doc_of[1:] != doc_of[:-1])])
    at = np.flatnonzero(new)
    length = np.diff(np.concatenate([at, [total]]))
    chosen = pick[at]
    prefix = prefix_names(hashes)
    s, c = start[at], np.maximum(chosen, 0)
    a = np.where(chosen >= 0, low[c], s)
    b = np.where(chosen >= 0, high[c], s + width)
    name = stretch_names(prefix, a, b) ^ mixed((begin[c] - a + 1).astype(np.uint64) * (chosen >= 0))
    around = stretch_names(prefix, s, s + length + width - 1) ^ mixed((a - s).astype(np.uint64))
    return doc_of[at], s, length, name, around, a - s, b - a


def signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64), pa.int64())


def anchors(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """``id, raw`` -> id, start, length, name, around, lead, span of each run of windows with one representative."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, "raw"):
            hashes, offsets = word_hashes(b.column("raw").to_pylist())
            doc, start, length, name, around, lead, span = anchored(hashes, offsets, width)
            short = lambda x: pa.array(x.astype(np.int32))
            yield pa.RecordBatch.from_arrays(
                [b.column("id").take(pa.array(doc)), short(start - offsets[doc]), short(length), signed(name), signed(around), short(lead), short(span)],
                ["id", "start", "length", "name", "around", "lead", "span"],
            )

    return docs.mapInArrow(run, "id long, start int, length int, name long, around long, lead int, span int")


def exploded(b: pa.RecordBatch, column: str) -> tuple[np.ndarray, dict[str, np.ndarray]]:
    """The row numbers and the fields of an array-of-structs column."""
    runs = b.column(column)
    counts = pc.fill_null(pc.list_value_length(runs), 0).to_numpy(zero_copy_only=False)
    flat = pc.list_flatten(runs)
    return np.repeat(np.arange(b.num_rows), counts), {f.name: flat.field(f.name).to_numpy(zero_copy_only=False).astype(np.int64) for f in flat.type}


def grouped_windows(docs: DataFrame, width: int = WIDTH, group: int = 4) -> DataFrame:
    """``id, raw, runs`` -> id, start, length, name of groups of at most ``group`` neighbouring windows.

    A group is fixed by the distance of its windows from their representative, and its name is that of the words they share. If a
    group's name is found once, none of its windows is found twice.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, "raw"):
            hashes, offsets = word_hashes(b.column("raw").to_pylist())
            row, r = exploded(b, "runs")
            if not len(row):
                continue
            each = np.repeat(np.arange(len(row)), r["length"])
            i = np.arange(len(each)) - np.repeat(np.cumsum(r["length"]) - r["length"], r["length"])
            left = r["lead"][each] - i  # words of the window before its representative's stretch
            level = left // group
            first = np.flatnonzero(np.concatenate([[True], (each[1:] != each[:-1]) | (level[1:] != level[:-1])]))
            e, size = each[first], np.diff(np.concatenate([first, [len(each)]]))
            near, at = level[first] * group, offsets[row[e]] + r["start"][e] + r["lead"][e]
            far = np.maximum(width - r["span"][e] - near - (group - 1), 0)
            # The left edge of a group may be cut by its run; what its windows share is counted from the full group all the same.
            name = stretch_names(prefix_names(hashes), at - near, at + r["span"][e] + far) ^ mixed((near * 64 + 1).astype(np.uint64))
            yield pa.RecordBatch.from_arrays([b.column("id").take(pa.array(row[e])), pa.array((r["start"][e] + i[first]).astype(np.int32)), pa.array(size.astype(np.int32)), signed(name)], ["id", "start", "length", "name"])

    return docs.mapInArrow(run, "id long, start int, length int, name long")


def window_rows(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """``id, raw, runs`` -> id, start and the 128-bit name of each window in ``runs`` (start, length)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, "raw"):
            raw = b.column("raw").to_pylist()
            hashes, offsets = word_hashes(raw)
            row, r = exploded(b, "runs")
            if not len(row):
                continue
            each = np.repeat(np.arange(len(row)), r["length"])
            place = r["start"][each] + np.arange(len(each)) - np.repeat(np.cumsum(r["length"]) - r["length"], r["length"])
            a = place + offsets[row[each]]
            one = stretch_names(prefix_names(hashes), a, a + width)
            two = stretch_names(prefix_names(word_hashes(raw, 2)[0]), a, a + width)
            yield pa.RecordBatch.from_arrays([b.column("id").take(pa.array(row[each])), pa.array(place.astype(np.int32)), signed(one), signed(two)], ["id", "start", "one", "two"])

    return docs.mapInArrow(run, "id long, start int, one long, two long")


def kept_words(raw: bytes, start: np.ndarray, length: np.ndarray, width: int = WIDTH) -> tuple[int, int, bytes]:
    """Number of words, number removed, the kept words joined by one space."""
    words = raw.split()
    if not len(start):
        return len(words), 0, b" ".join(words)
    gone = np.zeros(len(words) + 1, np.int32)
    np.add.at(gone, start, 1)
    np.add.at(gone, start + length + width - 1, -1)
    keep = np.flatnonzero(np.cumsum(gone[:-1]) == 0)
    return len(words), len(words) - len(keep), b" ".join([words[i] for i in keep.tolist()])


def again(rows: DataFrame, names: list[str], most: int = 1) -> DataFrame:
    """The rows (stored) whose ``names`` are found more than ``most`` times: counts are combined before the shuffle, then joined back.

    Names of more than a thousandth of all rows, of which there are fewer than a thousand, are joined by broadcast, so that none of them is one
    task's work.
    """
    counted = stored(rows.groupBy(*names).agg(F.count("*").alias("n")).filter(F.col("n") > most).select(*[F.col(c).alias(f"k{i}") for i, c in enumerate(names)], "n"))
    same = F.lit(True)
    for i, c in enumerate(names):
        same = same & (F.col(c) == F.col(f"k{i}"))
    often = max(HOT_ROWS, rows.count() // 1000)
    hot = counted.filter(F.col("n") > often).drop("n")
    if hot.isEmpty():
        return rows.join(counted.drop("n"), same, "left_semi")
    cold = counted.filter(F.col("n") <= often).drop("n")
    return rows.join(F.broadcast(hot), same, "left_semi").union(rows.join(F.broadcast(hot), same, "left_anti").join(cold, same, "left_semi"))


def repeats(texts: DataFrame, width: int = WIDTH) -> DataFrame:
    """``id, raw`` (bucketed by id) -> ``id, ranges``: runs of windows (start, length) whose words start at another place, too."""
    spark = texts.sparkSession

    def of_text(runs: DataFrame, *columns: str) -> DataFrame:
        lists = runs.groupBy("id").agg(F.collect_list(F.struct(*columns)).alias("runs"))
        return texts.join(lists, "id").select("id", "raw", "runs")

    some = stored(again(stored(anchors(texts.select("id", "raw"), width)), ["name"]))
    free_shuffles(spark)
    # The same surroundings twice: all windows of the run are repeated.
    units = some.groupBy("name", "around", "length").agg(F.count("*").alias("n")).filter("n > 1").select(F.col("name").alias("k"), F.col("around").alias("a"), F.col("length").alias("l"))
    marked = some.join(units, (F.col("name") == F.col("k")) & (F.col("around") == F.col("a")) & (F.col("length") == F.col("l")), "left")
    marked = stored(marked.select("id", "start", "length", "lead", "span", "name", F.col("k").isNotNull().alias("whole")))
    # A whole run still stands for its windows where others are compared with them; a name that has only whole runs is settled.
    loose = marked.filter(~F.col("whole")).select("name").distinct()
    to_name = marked.join(loose, "name", "left_semi")
    groups = stored(grouped_windows(of_text(to_name, "start", "length", "lead", "span"), width))
    free_shuffles(spark)
    groups = stored(again(groups, ["name"]).select("id", "start", "length"))
    windows = stored(window_rows(of_text(groups, "start", "length"), width))
    free_shuffles(spark)
    single = again(windows, ["one", "two"]).select("id", "start").distinct()
    # Neighbouring windows become one range again.
    island = single.withColumn("island", F.col("start") - F.row_number().over(Window.partitionBy("id").orderBy("start")))
    single = island.groupBy("id", "island").agg(F.min("start").alias("start"), F.count("*").cast("int").alias("length")).select("id", "start", "length")
    ranges = single.unionByName(marked.filter("whole").select("id", "start", "length"))
    out = stored(ranges.groupBy("id").agg(F.collect_list(F.struct("start", "length")).alias("ranges")))
    free_shuffles(spark)
    return out


def deduplicated(docs: DataFrame, width: int = WIDTH, with_text: bool = True) -> DataFrame:
    """One row a document: doc_id, n_words, n_removed, kept_sha256 and, unless left out, kept_text (null where the text is null).

    Null and blank texts have no words. Texts shorter than ``width`` words are left alone. Rows that repeat a text repeat all of its
    windows, also when they repeat the id. Extra columns are ignored.
    """
    ids = docs.agg(F.count("*").alias("n"), F.count_distinct("doc_id").alias("k")).first()
    # A number a row is known by: its id, or where ids repeat or are null a hash of id and text (equal rows share it, and their result).
    key = F.col("doc_id") if ids["n"] == ids["k"] else F.xxhash64("doc_id", "text")
    text = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    rows = docs.select(key.cast("long").alias("id"), F.col("doc_id").alias("doc_id"), text.alias("raw"), F.col("text").isNull().alias("none"))
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, "raw"):
            row, r = exploded(b, "ranges")
            at = np.searchsorted(row, np.arange(b.num_rows + 1))
            start, length = (r["start"], r["length"]) if len(row) else (np.zeros(0, np.int64),) * 2
            got = [kept_words(x, start[i:j], length[i:j], width) for x, i, j in zip(b.column("raw").to_pylist(), at[:-1], at[1:], strict=True)]
            out = [b.column("doc_id"), pa.array([g[0] for g in got], pa.int64()), pa.array([g[1] for g in got], pa.int64()), pa.array([hashlib.sha256(g[2]).hexdigest() for g in got], pa.string())]
            names = ["doc_id", "n_words", "n_removed", "kept_sha256"]
            if with_text:
                none = b.column("none").to_pylist()
                out, names = [*out, pa.array([None if x else g[2].decode("utf-8", "replace") for g, x in zip(got, none, strict=True)], pa.string())], [*names, "kept_text"]
            yield pa.RecordBatch.from_arrays(out, names)

    with bucketed(rows, "id") as texts:
        both = texts.join(repeats(texts.select("id", "raw"), width), "id", "left").select("doc_id", "raw", "none", "ranges")
        schema = f"doc_id {kind}, n_words long, n_removed long, kept_sha256 string" + ", kept_text string" * with_text
        return stored(both.mapInArrow(run, schema))


def op2(spark, sf_dir: str) -> DataFrame:
    return deduplicated(table(spark, sf_dir, "documents"), with_text=False)


def brute_force(texts: list[str | None], width: int = WIDTH) -> list[tuple[int, int, str]]:
    """Every window in a dictionary, for tests."""
    words = [(t or "").encode().split() for t in texts]
    seen: dict[tuple, int] = {}
    for w in words:
        for i in range(len(w) - width + 1):
            seen[tuple(w[i : i + width])] = seen.get(tuple(w[i : i + width]), 0) + 1
    out = []
    for w in words:
        gone = {k for i in range(len(w) - width + 1) if seen[tuple(w[i : i + width])] > 1 for k in range(i, i + width)}
        kept = b" ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((len(w), len(gone), hashlib.sha256(kept).hexdigest()))
    return out
