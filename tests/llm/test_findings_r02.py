"""Cases of the second review of the corpus operators."""

from collections import defaultdict

import hashlib
import math
import re

from graphevents.llm import licences, nearcopies


def test_statements_without_a_licence_word_are_found(spark):
    files = [(1, "a/x", "some code\nUnauthorized copying of this file is prohibited.\n" + "more words here " * 30), (2, "b/y", "this file is a copy of that file\n" + "more words " * 30)]
    got = {r["id"]: (r["license"], r["origin"]) for r in licences.scanned(spark.createDataFrame(files, "id long, path string, text string")).collect()}
    assert got == {1: ("Proprietary", "header"), 2: (None, "none")}


def test_bounds_never_let_go_of_a_match(spark, sf):
    """Every line of the table against all templates, without any sieve, gives the same lines at or above the threshold."""
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("text").collect()
    lines = sorted({x for d in docs for x in (d["text"] or "").split("\n")} | {"unauthorized copying is prohibited", "use of this file: not prohibited, not prohibited"})
    terms = lambda x: re.findall(licences.TERM, x.lower())
    idf = defaultdict(lambda: 2.5, {t: 1.0 + 0.1 * (len(t) % 7) for x in licences.TEMPLATES.values() for t in terms(x)})

    def unit(x):
        w = {t: (1 + math.log(terms(x).count(t))) * idf[t] for t in set(terms(x))}
        norm = math.sqrt(sum(v * v for v in w.values()))
        return {t: v / norm for t, v in w.items()}

    templates = {k: unit(v) for k, v in licences.TEMPLATES.items()}
    rows = [{"template": k, "term": t, "v": v, "idf": idf[t]} for k, of in templates.items() for t, v in of.items()]
    sieve = licences.Sieve(rows, licences.THRESHOLD)
    kept = {r["line"]: (r["a"], r["b"]) for r in spark.createDataFrame([(x,) for x in lines], "line string").select("line", sieve.may_hold("line").alias("a"), sieve.may_match("line").alias("b")).collect()}
    some = 0
    for x in lines:
        mine = unit(x) if terms(x) else {}
        if max(sum(v * of.get(t, 0.0) for t, v in mine.items()) for of in templates.values()) >= licences.THRESHOLD:
            some += 1
            assert kept[x] == (True, True), x
    assert some > 2 and sum(b for _, b in kept.values()) < len(lines) / 4


def test_texts_stay_where_they_are(spark, tmp_path):
    """With joins by a shuffle, as on large tables, no stage writes the texts to disk; other texts of a path count among its words."""
    long = lambda i: " ".join(hashlib.md5(f"{i} {k}".encode()).hexdigest() for k in range(150))
    files = [(i, f"a/{i}", long(i)) for i in range(300)] + [(900, "b/x", "Released under the MIT License."), (901, "b/x", "other words"), (902, "b/y", "one")]
    spark.createDataFrame(files, "id long, path string, text string").write.parquet(f"{tmp_path}/files")
    written = lambda: int(spark.sparkContext._jsc.sc().statusStore().executorSummary("driver").totalShuffleWrite())
    limit = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    spark.conf.set("spark.sql.adaptive.autoBroadcastJoinThreshold", "-1")
    try:
        before = written()
        found, sizes = licences.line_matches(spark.read.parquet(f"{tmp_path}/files").select("path", "text"))
        some, words = found.collect(), sizes.collect()
        moved = written() - before
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", limit)
        spark.conf.unset("spark.sql.adaptive.autoBroadcastJoinThreshold")
    assert [(r["path"], r["n_words"], r["license"]) for r in some] == [("b/x", 5, "MIT")] and [(r["path"], r["words"]) for r in words] == [("b/x", 7)]
    assert moved < 100_000, moved


def test_buckets_of_like_lengths_are_not_doubled(spark, tmp_path):
    """Two classes of length are one band, with a row for each; over more classes, all pairs whose lengths allow a link still meet."""
    like = [(1, i, n, i) for i, n in enumerate((100, 104, 120, 99, 110, 118))]
    wide = [(2, i, n, i % 5) for i, n in enumerate((10, 12, 13, 16, 20, 24, 25, 31, 40, 50, 51))]
    one = [(3, i, 100, 7) for i in range(4)]
    rows = nearcopies.banded(spark.createDataFrame(like + wide + one, "key long, id long, n long, comp long"), 0.8).collect()
    assert len([r for r in rows if r["key"] == 1]) == len(like) and len({r["band"] for r in rows if r["key"] == 1}) == 1 and not [r for r in rows if r["key"] == 3]
    bands = defaultdict(set)
    for r in rows:
        bands[r["key"], r["id"]].add(r["band"])
    for k, i, n, _ in like + wide:
        for m, j, o, _ in like + wide:
            if k == m and min(n, o) >= 0.8 * max(n, o):
                assert bands[k, i] & bands[m, j], (n, o)


def test_buckets_that_a_tile_holds_are_not_doubled(spark, monkeypatch):
    """A bucket of many lengths is one band, with a row for each; beyond a tile it is divided, and all pairs whose lengths allow a link still meet."""
    lengths = (10, 12, 13, 16, 20, 24, 25, 31, 40, 50, 51, 300)
    rows = spark.createDataFrame([(1, i, n, i % 5) for i, n in enumerate(lengths)] + [(2, i, n, 7) for i, n in enumerate(lengths)], "key long, id long, n long, comp long")
    got = nearcopies.banded(rows, 0.8).collect()
    assert sorted((r["key"], r["id"], r["n"], r["comp"]) for r in got) == [(1, i, n, i % 5) for i, n in enumerate(lengths)] and len({r["band"] for r in got}) == 1
    monkeypatch.setattr(nearcopies, "TILE", 4)
    bands, members = defaultdict(set), defaultdict(set)
    for r in nearcopies.banded(rows, 0.8).collect():
        assert r["key"] == 1
        bands[r["id"]].add(r["band"])
        members[r["band"]].add(r["comp"])
    assert len(members) > 3 and all(len(x) > 1 for x in members.values())
    for i, n in enumerate(lengths):
        for j, o in enumerate(lengths):
            if i % 5 != j % 5 and min(n, o) >= 0.8 * max(n, o):
                assert bands[i] & bands[j], (n, o)
