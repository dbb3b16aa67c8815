"""Corpus operators against brute force, round trips and edge cases."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from graphevents.llm import licences, mixing, nearcopies, pieces, quality, secrets, sharding, substrings, toxicity, vectors

ODD = [(1, None, "en", "a", 0), (2, "", "en", None, 0), (3, "  \n\t ", None, "a", 3), (4, "one two", "en", "a", 7), (4, "one two", "en", "a", 7), (None, "x y z", "de", "b", 5), (7, "word " * 6000, "fr", "b", 30000)]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA).withColumn("row", F.lit(1)).withColumn("size", F.lit("x")).withColumn("ids", F.lit(0))


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (4, 0, 1), (None, 1, 1)], "doc_id long, quality int, toxic int")


def prose(n, seed):
    rng = random.Random(seed)
    return [" ".join(rng.choice(["ab", "cd", "ef", "gh", "ij", "kl"]) + str(rng.randint(0, 300)) for _ in range(rng.randint(5, 90))) for _ in range(n)]


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "en", f"s{i % 3}", len(t or "")) for i, t in enumerate(texts)], SCHEMA)


def test_every_operator_takes_odd_rows_and_empty_tables(spark, odd, labels):
    for docs in (odd, odd.limit(0)):
        n = docs.count()
        assert mixing.mix(spark, docs).count() == n
        assert substrings.deduplicated(docs).count() == n
        assert toxicity.scored(docs, toxicity.fitted(toxicity.sample(docs, labels))).filter("score between 0 and 1").count() == n
        assert pieces.encoded(docs).count() == n
        assert quality.judge(docs, labels).count() == n
        assert quality.kept_documents(docs, labels).columns == docs.columns
        assert sharding.sharded(docs).count() == n
        assert secrets.report(docs).count() == n
        assert secrets.clean_documents(docs).count() == n
        assert nearcopies.classes(docs).count() == n
        assert mixing.mixed_documents(docs).columns == docs.columns
        assert licences.scanned(docs.select(F.col("doc_id").alias("id"), F.concat_ws("/", "source", "doc_id").alias("path"), "text")).count() == n


def test_repeated_passages_against_brute_force(spark):
    texts = prose(30, 1)
    texts += [texts[0], texts[3] + " x " + texts[4], "q " * 90, " ".join(["p", "r"] * 60), None, texts[5][: len(texts[5]) // 2] + " tail of another kind"]
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substrings.deduplicated(frame(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == substrings.brute_force(texts)


def test_edit_distance_against_a_table():
    rng = random.Random(3)

    def table(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            new = [i]
            for j, y in enumerate(b, 1):
                new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
            row = new
        return row[-1]

    for _ in range(400):
        a, b = ([rng.choice("abcd") for _ in range(rng.randint(0, 25))] for _ in range(2))
        d = table(a, b)
        for most in (0, 2, 5, 9, 40):
            assert nearcopies.edit_distance(a, b, most) == (d if d <= most else most + 1)


def test_near_copies_against_all_pairs(spark):
    rng = random.Random(8)
    texts = prose(25, 2)
    for k in range(12):
        w = texts[k].split()
        for _ in range(max(1, len(w) // 20)):
            w[rng.randrange(len(w))] = "edit" + str(rng.randint(0, 9))
        texts.append(" ".join(w))
    texts += [texts[1], texts[1]]
    up = list(range(len(texts)))
    words = [t.split() for t in texts]
    for i in range(len(texts)):
        for j in range(i):
            most = int(0.2 * max(len(words[i]), len(words[j])) + 1e-9)
            if nearcopies.edit_distance(words[i], words[j], most) <= most:
                lo, hi = sorted((up[i], up[j]))
                up = [lo if u == hi else u for u in up]
    got = {r["doc_id"]: r["class_id"] for r in nearcopies.classes(frame(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == up


def test_texts_left_by_the_first_leader_are_compared(spark):
    words = [f"w{i}" for i in range(40)]
    texts = ["other " * 40, " ".join(words), " ".join(words[:36] + ["x"] * 4)]
    rows = spark.createDataFrame([(i, 40, bytearray(t.encode()), 7, 3, i) for i, t in enumerate(texts)], "id long, n long, raw binary, key long, k long, doc long")
    with nearcopies.bucketed(nearcopies.with_bins(rows), "id") as kept:
        assert sorted(tuple(r) for r in nearcopies.linked(rows.drop("raw"), kept, spark.createDataFrame([], "src long, dst long"), 0.8).collect()) == [(1, 1), (2, 1)]


def test_a_text_linked_through_a_longer_one_is_compared(spark):
    words = [f"w{i}" for i in range(125)]
    texts = [words[:100], words, words[25:]]
    rows = spark.createDataFrame([(i, len(t), bytearray(" ".join(t).encode()), 7, 3, i) for i, t in enumerate(texts)], "id long, n long, raw binary, key long, k long, doc long")
    with nearcopies.bucketed(nearcopies.with_bins(rows), "id") as kept:
        assert sorted(tuple(r) for r in nearcopies.linked(rows.drop("raw"), kept, spark.createDataFrame([], "src long, dst long"), 0.8).collect()) == [(0, 0), (1, 0), (2, 0)]


def test_mix_meets_targets(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = mixing.mix(spark, docs).toPandas().merge(docs.select("doc_id", "source").toPandas(), on="doc_id")
    assert (rows.taken <= 2 * rows["size"]).all()
    per = rows.groupby("source").agg(size=("size", "sum"), target=("target", "first"), taken=("taken", "sum"))
    assert abs(per.target.sum() - 1.5 * per["size"].sum()) < 1e-6 * per["size"].sum() and (per.target <= 2 * per["size"] + 1e-6).all()
    # The guarantee: the gap before the first document that no longer fits, or what that one would go over, whichever is smaller.
    assert (abs(per.taken - per.target) <= rows.groupby("source")["size"].max() / 2 + 1).all()


def test_targets_by_resharing(spark):
    sizes, weights = [10.0, 100.0, 40.0, 7.0], [3, 1, 2, 3]
    total, full, level = 1.5 * sum(sizes), set(), []
    while True:
        rest = total - sum(2 * sizes[i] for i in full)
        mass = sum(w for i, w in enumerate(weights) if i not in full)
        level = [2 * s if i in full else rest * weights[i] / mass for i, s in enumerate(sizes)]
        over = {i for i, t in enumerate(level) if t > 2 * sizes[i] + 1e-9}
        if not over:
            break
        full |= over
    df = spark.createDataFrame([(f"s{i}", s, w) for i, (s, w) in enumerate(zip(sizes, weights, strict=True))], "source string, source_size double, weight int")
    got = [r["target"] for r in mixing.targets(df, 1.5, 2.0).orderBy("source").collect()]
    assert got == pytest.approx(level)


def test_vector_links_against_all_pairs(spark):
    rng = np.random.default_rng(2)
    base = rng.normal(size=(6, 8))
    rows = [(i, [float(x) for x in base[i % 6] + rng.normal(0, 0.12, 8)], i % 2) for i in range(60)]
    rows += [(60, rows[0][1], 0), (61, None, 0), (62, [0.0] * 8, 0), (63, [float("nan")] + [1.0] * 7, 1), (64, rows[1][1], None), (65, [x * 5 for x in rows[0][1]], 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    want = vectors.brute_force(df.toPandas()).set_index("vec_id")
    for tile in (1024, 7):
        got = vectors.near_duplicates(df, tile=tile).toPandas().set_index("vec_id").loc[want.index]
        assert (got.n_links == want.n_links).all() and (got.component_id == want.component_id).all()


def test_quantised_bound_holds():
    rng = np.random.default_rng(0)
    u = rng.normal(size=(50, 16))
    u /= np.linalg.norm(u, axis=1)[:, None]
    q, s, length, error = vectors.quantised(u)
    about = (q.astype(float) @ q.T.astype(float)) * s[:, None] * s[None]
    assert (np.abs(about - u @ u.T) <= length[:, None] * error[None] + error[:, None] + 1e-12).all()


def test_shards_are_even_and_gapless(spark, sf):
    rows = sharding.sharded(spark.read.parquet(f"{sf}/documents.parquet"), range_rows=20).toPandas()
    for _, g in rows.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g)))
    by = rows.groupby("shard")["size"].sum()
    assert len(by) == 24 and by.max() - by.min() <= 2 * rows["size"].max()
    again = sharding.sharded(spark.read.parquet(f"{sf}/documents.parquet"), range_rows=1000).toPandas()
    key = ["doc_id", "shard", "slot"]
    assert (rows.sort_values("doc_id")[key].values == again.sort_values("doc_id")[key].values).all()


def test_binomial_bound():
    assert abs(quality.binomial_tail(2, 10, 0.3) - 0.3827827864) < 1e-9
    assert quality.certified(0, 150, 0.02, 0.05) and not quality.certified(0, 140, 0.02, 0.05)


def test_counts_of_a_text():
    t = "a b c d e a b c d e\nsame\nsame\n#*| x"
    n, chars, symbols, dup, repeat, shout = quality.text_counts(t.encode())
    assert (n, chars, symbols, dup, repeat) == (14, 22, 3, 1, 10)


def test_secret_structures():
    import base64
    import json

    def der(tag, body):
        size = bytes([len(body)]) if len(body) < 128 else bytes([0x82]) + len(body).to_bytes(2, "big")
        return bytes([tag]) + size + body

    num = lambda k: der(2, b"\x01" * k)
    key = der(0x30, der(2, b"\x00") + num(64) + num(3) + num(64) + num(32) * 2 + num(32) * 3)
    b64 = base64.b64encode(key).decode()
    assert [k for _, _, k in secrets.spans_of(f"x {b64} y")] == ["private_key"]
    assert "private_key" in [k for _, _, k in secrets.spans_of(f"x {key.hex()} y")]
    assert secrets.spans_of("x " + base64.b64encode(b"\x55" * 90).decode() + " y") == []
    part = lambda o: base64.urlsafe_b64encode(json.dumps(o).encode()).decode().rstrip("=")
    token = f"{part({'alg': 'HS256', 'typ': 'JWT'})}.{part({'sub': 1})}.c2lnbmF0dXJl"
    assert [s for s in secrets.spans_of(f"see {token} .") if s[2] == "signed_token"] == [(4, 4 + len(token), "signed_token")]
    assert secrets.spans_of('Password: "abcdefgh" AKIA' + "A" * 12) == [(0, 19, "assign"), (21, 37, "access")]
    assert secrets.redacted("abcdef", [(1, 3), (2, 4)]) == "a[secret]ef"


def test_pieces_equal_the_library_and_come_back():
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=pieces.MODEL)
    m = pieces.Pieces(pieces.MODEL)
    texts = ["", "a", "  ab  c", "\n\n x\t\ty", "日本語 テスト", "é́ﬁ ßtest   ", "hello world" * 20, "def f(x):\n        return  x", "😀 family", "aaaaaaaaaaaaaaaa", "-----====", " " * 9, *prose(40, 5)]
    assert [x.tolist() for x in m.encode(texts)] == sp.encode(texts)
    assert [m.decode(x.tolist()) for x in m.encode(texts)] == texts


def test_toxic_clauses():
    stems = {"moron": 3.0}
    found = lambda t: [p for p, _ in toxicity.clause_patterns(t.split(), stems)]
    assert found("you are a moron") == ["aimed"]
    assert found("the moron case") == ["plain"]
    assert found("that is not a moron") == ["negated"]
    assert found("somebody wrote that moron thing") == ["reported"]
    assert found("i will hurt you") == ["threat"]


def test_toxicity_on_held_out_rows(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    rows = toxicity.scored(docs, toxicity.fitted(toxicity.sample(docs, labels))).join(labels, "doc_id").filter("held_out").toPandas()
    assert (rows.predicted == rows.toxic).mean() > 0.93


def test_licences_and_inheritance(spark):
    files = [(1, "a/LICENSE", "Released under the MIT License."), (2, "a/b/x", "some code"), (3, "a/b/y", "code\nLicensed under CC BY-NC 4.0.\n" + "more words " * 30), (4, "c/z", "nothing"), (5, None, "Released under the MIT License."), (6, "a/b/c/d", None)]
    got = {r["id"]: (r["license"], r["origin"], r["inherited_from"]) for r in licences.scanned(spark.createDataFrame(files, "id long, path string, text string")).collect()}
    assert got[1] == ("MIT", "file", None) and got[2] == ("MIT", "inherited", "a") and got[3] == ("CC-BY-NC-4.0", "header", None)
    assert got[4] == (None, "none", None) and got[6] == ("MIT", "inherited", "a") and got[5][1] == "none"


@pytest.mark.parametrize("size", ["sf0.001", "sf0.01"])
def test_every_licence_line_of_the_tables_is_found(spark, size):
    docs = spark.read.parquet(f"/root/testdata/{size}/documents.parquet").select(F.col("doc_id").cast("string").alias("path"), "text")
    lines = docs.select("path", F.explode(F.split("text", "\n")).alias("line")).filter(F.col("line").rlike(licences.CUE))
    found = licences.line_matches(docs)[0].groupBy("path").agg(F.collect_set("license").alias("l"))
    assert lines.join(found, "path", "left_anti").count() == 0
    reserved = lines.filter("line = 'All rights reserved.'").join(found, "path").filter("array_contains(l, 'Proprietary')")
    assert reserved.count() == lines.filter("line = 'All rights reserved.'").count() > 0


def test_a_wrapped_statement_is_found_by_its_block(spark):
    text = "# Licensed under the\n# Apache License,\n# Version 2.0.\n\n" + "some code here " * 30
    got = licences.scanned(spark.createDataFrame([(1, "a/x", text)], "id long, path string, text string")).first()
    assert (got["license"], got["origin"]) == ("Apache-2.0", "header")


def test_pipeline_stages(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = corpus_pipeline.quality_rules(spark, docs, sf)
    assert kept.columns == docs.columns and 0 < kept.count() <= docs.count()
    assert corpus_pipeline.near_copies(spark, kept, sf).columns == docs.columns
    clean = corpus_pipeline.secret_scan(spark, kept, sf)
    assert secrets.report(clean).filter("n_assign + n_access + n_hex > 0").count() == 0 and clean.count() == kept.count()
    assert corpus_pipeline.run(spark, sf).filter("not round_trip").count() == 0
