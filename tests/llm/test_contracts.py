"""Corpus queries against plain versions of their contracts, and values on odd rows."""

import base64
import hashlib
import random
import re
import zlib

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from graphevents.llm import licences, mixing, nearcopies, pieces, quality, queries, secrets, sharding, substrings, toxicity, vectors

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def texts(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").toPandas()


def test_the_mix_against_sql(spark, sf):
    import duckdb

    con = duckdb.connect()
    con.sql(f"create view documents as select * from '{sf}/documents.parquet'")
    want = {r[0]: r[1:] for r in con.sql(queries.MIX).fetchall()}
    got = {r["doc_id"]: (r["size"], r["source_size"], r["target"], r["taken"]) for r in mixing.op1(spark, sf).collect()}
    assert got == want


def test_the_mix_is_unequal_and_redistributes_certain_documents(spark):
    docs = spark.createDataFrame([(i, "w " * (400 if i < 4 else 4), "en", "a", 0) for i in range(400)] + [(1000 + i, "w " * 3000, "en", "b", 0) for i in range(5)], SCHEMA)
    rows = mixing.mix(spark, docs).toPandas()
    small, large = rows[(rows.doc_id >= 4) & (rows.doc_id < 1000)], rows[rows.doc_id < 4]
    assert (large.taken > 0).all()  # in proportion to words, the few long ones are certain or nearly so
    assert (rows.taken <= 2 * rows["size"]).all() and (rows.taken % rows["size"] == 0).all()
    assert abs(rows[rows.doc_id < 1000].taken.sum() - small.target.iloc[0]) <= 200


def test_quality_counts_against_brute_force(spark, sf, texts):
    got = {r["doc_id"]: r for r in quality.op6(spark, sf).collect()}
    for doc_id, text in zip(texts.doc_id, texts.text, strict=True):
        text = text or ""
        words, r = WORD.findall(text), got[doc_id]
        lines = [x for x in text.split("\n") if WORD.search(x)]
        seen, places = {}, set()
        for i in range(len(words) - 4):
            seen.setdefault(tuple(words[i : i + 5]), []).append(i)
        for at in seen.values():
            if len(at) > 1:
                places.update(k for i in at for k in range(i, i + 5))
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (
            len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(places)), doc_id
        failed = len(words) < 10 or 100 * len(places) > 20 * len(words)
        assert r["base_failed"] == failed and not (failed and r["kept"])


def test_shards_keep_equal_texts_and_sizes(spark, sf, texts):
    rows = sharding.op8(spark, sf).toPandas().merge(texts[["doc_id", "text"]], on="doc_id")
    raw = [(t or "").encode() for t in rows.text]
    assert (rows["size"] == [len(x) + 8 for x in raw]).all() and (rows.text_crc32 == [zlib.crc32(x) for x in raw]).all()
    assert rows.groupby(rows.text.fillna("")).shard.nunique().max() == 1
    per = rows.groupby("shard")["size"].sum()
    assert len(per) == 24 and per.max() - per.min() <= 2 * max(1, per.mean() / 20)
    assert all(sorted(s) == list(range(len(s))) for _, s in rows.groupby("shard").slot)


def test_a_group_heavier_than_a_shard_is_divided_and_none_other(spark):
    docs = spark.createDataFrame([(i, "a b c " * 50 if i < 40 else "x" * (i % 97 + 1)) for i in range(300)] + [(1000 + i, None if i % 2 else "") for i in range(100)], "doc_id long, text string")
    rows = sharding.sharded(docs).toPandas()
    assert (rows.groupby("text_crc32").shard.nunique() > 1).sum() == 1
    per = rows.groupby("shard")["size"].sum()
    assert per.max() <= 1.1 * per.mean()


def test_groups_are_dealt_to_the_emptiest_shard_and_rooms_filled_to_one_level():
    of, upto = sharding.dealt([("a", 90), ("b", 30), ("c", 250)], 600, 6)
    assert len({of["c", 0], of["c", 1], of["c", 2]}) == 3 and {k for k, _ in of} == {"a", "b", "c"}
    assert abs(upto[-1] - (600 - 370)) < 1e-6 and upto == sorted(upto)


def base_spans(text):
    found = [(m.start(), m.end(), "assign") for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text, re.I | re.A) if len(m[2]) >= 8]
    found += [(m.start(), m.end(), "access") for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 16]
    return found + [(m.start(), m.end(), "hex") for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 32]


def test_base_spans_against_plain_patterns(spark, sf, texts):
    order = ("assign", "access", "hex")
    got = {r["doc_id"]: r for r in secrets.op9(spark, sf).collect()}
    for doc_id, text in zip(texts.doc_id, texts.text, strict=True):
        spans = sorted(base_spans(text or ""), key=lambda s: (s[0], order.index(s[2])))
        assert got[doc_id]["base_sha256"] == hashlib.sha256(",".join(f"{k}:{a}:{b}" for a, b, k in spans).encode()).hexdigest()
        assert [got[doc_id][f"n_{k}"] for k in order] == [sum(s[2] == k for s in spans) for k in order]


def tlv(tag, body):
    n = len(body)
    return bytes([tag]) + (bytes([n]) if n < 128 else bytes([0x82]) + n.to_bytes(2, "big")) + body


def test_keys_are_found_wrapped_at_odd_places_and_with_header_lines():
    rng = random.Random(1)
    some = lambda n: bytes(rng.randrange(1, 120) for _ in range(n))
    key = tlv(0x30, tlv(2, b"\0") + tlv(2, some(128)) + tlv(2, b"\1\0\1") + b"".join(tlv(2, some(64)) for _ in range(6)))
    flat = base64.b64encode(key).decode()
    wrapped = "\n".join(flat[i : i + 64] for i in range(0, len(flat), 64))
    begin, end = "-----BEGIN RSA PRIVATE KEY-----\n", "\n-----END RSA PRIVATE KEY-----"
    locked = "Proc-Type: 4,ENCRYPTED\nDEK-Info: AES-128-CBC,0123456789ABCDEF0123456789ABCDEF\n\n" + base64.b64encode(some(608)).decode()
    deep = lambda t: [s for s in secrets.spans_of(t) if s[2] not in ("assign", "access", "hex")]
    assert deep(f"the key {flat} ends") == [(8, 8 + len(flat), "private_key")]
    assert deep(f"the\n{wrapped}\nThe end") == [(4, 4 + len(wrapped), "private_key")]
    for body in (wrapped, "Comment: mine\n\n" + wrapped, locked):
        assert deep(begin + body + end) == [(0, len(begin + body + end), "private_key")]
    for lead in ("", "a", "ab", "f0e"):
        assert deep(lead + key.hex()) == [(len(lead), len(lead) + 2 * len(key), "private_key")]
    assert deep(key.hex().upper()) and not deep(base64.b64encode(some(400)).decode()) and not deep(some(300).hex())


def test_toxicity_transducers_compose_and_read_both_ways():
    of = lambda t: toxicity.clause_patterns(t.split(), toxicity.SEEDS)
    assert of("you are a moron") == [("aimed", 3.0)] and of("moron") == [("plain", 3.0)]
    assert of("he said you are a moron") == of("you are a moron said nobody") == [("reported", 3.0)]
    assert of("you are not a moron") == [("negated", 3.0)] and of("i will kill you") == [("threat", 1.0)] and of("i never will kill you") == []
    alphabet = toxicity.alphabet_of(("negation", "target"))
    one, two = toxicity.reaching("negation", 2, alphabet), toxicity.reaching("target", 3, alphabet)
    rng = random.Random(2)
    for _ in range(50):
        read = [((rng.choice(toxicity.SYMBOLS), frozenset()), rng.random()) for _ in range(12)]
        assert toxicity.composed(one, two).run(read) == two.run(one.run(read))


def test_toxicity_beats_always_answering_no(spark):
    sf = "/root/testdata/sf0.1"
    rows = toxicity.op3(spark, sf).filter("held_out").join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").toPandas()
    hit = ((rows.predicted == 1) & (rows.toxic == 1)).sum()
    assert hit / (rows.toxic == 1).sum() >= 0.85 and hit / (rows.predicted == 1).sum() >= 0.9


def test_wrapped_headers_whole_licence_files_and_inheritance(spark):
    files = [("a/b/LICENSE", licences.TEMPLATES["MIT  "].replace(". ", ".\n")), ("a/b/x.py", "# a long file with words\n# This work is licensed under the\n# GNU General Public License,\n# version 3.\nimport foo and more words here\nbar baz " + "qux " * 20),
             ("a/b/c/y.py", "nothing"), ("z", "All rights reserved."), (None, None), ("q/r", ""), ("a/b/x.py", "word " * 20_000)]
    rows = spark.createDataFrame([(i, p, t) for i, (p, t) in enumerate(files)], "id long, path string, text string").withColumn("license", F.lit("clash"))
    got = {r["id"]: (r["license"], r["origin"]) for r in licences.scanned(rows).collect()}
    assert got == {0: ("MIT", "file"), 1: ("GPL-3.0", "header"), 2: ("MIT", "inherited"), 3: ("Proprietary", "file"), 4: (None, "none"), 5: (None, "none"), 6: ("GPL-3.0", "header")}


def similar(a, b):
    n = max(len(a), len(b))
    return n and nearcopies.edit_distance(a, b, int(0.2 * n + 1e-9)) <= int(0.2 * n + 1e-9)


def test_near_copies_of_planted_families_near_the_threshold(spark):
    rng = random.Random(5)
    rows, family = [], 0
    for share in (0.02, 0.05, 0.08):
        for _ in range(12):
            base = [f"w{rng.randrange(5000)}" for _ in range(rng.randrange(60, 200))]
            for _ in range(8):
                rows.append([f"x{rng.randrange(9999)}" if rng.random() < share else w for w in base])
            family += 1
    docs = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(rows)], "doc_id long, text string")
    got = [r["class_id"] for r in nearcopies.classes(docs).orderBy("doc_id").collect()]
    links = [(i, j) for i in range(len(rows)) for j in range(i) if similar(rows[i], rows[j])]
    assert len(links) > 500 and sum(got[i] == got[j] for i, j in links) >= 0.99 * len(links)
    assert all(i // 8 == c // 8 for i, c in enumerate(got))


def test_the_leader_links_texts_whose_histograms_differ_both_ways(spark):
    words = [f"w{i}" for i in range(60)]
    other = [*words[:20], *[f"v{i}" for i in range(6)], *words[26:]]
    far = [*words[:20], *[f"u{i}" for i in range(20)], *words[40:]]
    rows = spark.createDataFrame([(i, len(w), " ".join(w).encode()) for i, w in enumerate([words, other, far])], "id long, n long, raw binary")
    pairs = spark.createDataFrame([(0, 1), (0, 2), (1, 2)], "a long, b long")
    with nearcopies.bucketed(nearcopies.with_bins(rows), "id") as kept:
        assert [tuple(r) for r in nearcopies.compared(pairs, kept, 0.2).collect()] == [(0, 1, 60, 60, 6)]


def test_tiles_give_what_packs_give(spark, monkeypatch):
    rng = random.Random(6)
    passage = [f"p{k}" for k in range(60)]
    rows = [passage + [f"w{rng.randrange(3000)}" for _ in range(rng.randrange(8, 90))] for _ in range(80)]
    docs = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(rows)], "doc_id long, text string")
    whole = nearcopies.classes(docs).orderBy("doc_id").collect()
    for name, value in (("TILE", 7), ("TEXT_TILE", 3), ("PACK_ROWS", 16), ("PACK_WORDS", 500), ("FEW", 0)):
        monkeypatch.setattr(nearcopies, name, value)
    assert nearcopies.classes(docs).orderBy("doc_id").collect() == whole
    links = [(i, j) for i in range(80) for j in range(i) if similar(rows[i], rows[j])]
    found = [r["class_id"] for r in whole]
    assert sum(found[i] == found[j] for i, j in links) >= 0.9 * len(links)


def test_distinct_documents_on_repeated_ids_and_clashing_names(spark):
    docs = spark.createDataFrame([(1, "a b c"), (1, "a b c"), (1, None), (2, "a b c"), (3, ""), (None, "a b c"), (4, "z " * 9)], "doc_id long, text string").withColumn("kept_id", F.lit(1)).withColumn("rows", F.lit(2))
    got = nearcopies.distinct_documents(docs)
    assert got.columns == docs.columns and sorted(str(r["doc_id"]) for r in got.collect()) == ["1", "3", "4", "None"]
    assert nearcopies.distinct_documents(docs.limit(0)).count() == 0


def test_vector_links_on_empty_tables_and_clashing_names(spark):
    rows = [(1, [1.0, 0.0], 0), (2, [1.0, 0.01], 0), (3, None, 0), (4, [0.0, 0.0], 0), (5, [1.0, 0.0], None), (6, [1.0, 0.0], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").withColumn("n_links", F.lit(9)).withColumn("component", F.lit(9))
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in vectors.near_duplicates(df).collect()}
    assert got == {1: (1, 1), 2: (1, 1), 3: (0, 3), 4: (0, 4), 5: (0, 5), 6: (0, 6)}
    assert vectors.near_duplicates(df.limit(0)).count() == 0


def test_pieces_by_bytes_equal_the_library(texts):
    import sentencepiece

    model, lib = pieces.pieces(), sentencepiece.SentencePieceProcessor(model_file=pieces.MODEL)
    some = [t or "" for t in texts.text[:80]] + ["", " ", "a  b", " a", "a ", "\n a\tb", "▁x y"]
    for text, ids in zip(some, model.encode(some), strict=True):
        assert ids.tolist() == lib.encode(text)
        assert "▁" in text or model.decode(ids.tolist()) == text


def test_substrings_with_hot_names(spark, monkeypatch):
    monkeypatch.setattr(substrings, "HOT_ROWS", 3)
    rng = random.Random(8)
    shared = " ".join(f"s{k}" for k in range(50))
    texts = [" ".join(f"w{rng.randrange(900)}" for _ in range(20)) + " " + shared for _ in range(12)] + ["q " * 200, "solo text"]
    rows = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], SCHEMA)
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substrings.deduplicated(rows).collect()}
    assert [got[i] for i in range(len(texts))] == substrings.brute_force(texts)


def test_the_pipeline_stage_by_stage(spark, tmp_path):
    """Each stage on what the one before it kept, against plain versions."""
    rng = random.Random(9)
    word = lambda: f"w{rng.randrange(4000)}"
    body = [" ".join(word() for _ in range(60)) for _ in range(12)]
    rows = [(i, t, "en", f"s{i % 2}", len(t)) for i, t in enumerate(body)]
    rows += [(20, body[3], "en", "s1", 0), (21, body[4] + " extra", "en", "s0", 0), (22, "too short", "en", "s0", 9), (23, None, None, None, None), (24, "x y " * 40, "en", "s1", 0), (25, body[5] + " token=abcdefgh12345", "de", "s1", 0)]
    spark.createDataFrame(rows, SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(0, 1, 0), (22, 0, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs, after = spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, str(tmp_path))
        docs.write.parquet(f"{tmp_path}/{name}")
        docs = spark.read.parquet(f"{tmp_path}/{name}")
        after[name] = docs.toPandas()
    assert sorted(after["quality_rules"].doc_id) == [*range(12), 20, 21, 25]
    assert sorted(after["near_copies"].doc_id) == list(range(12))
    assert not after["secret_scan"].text.str.contains("abcdefgh12345").any()
    want = {r["doc_id"]: r["taken"] // r["size"] for r in mixing.mix(spark, spark.read.parquet(f"{tmp_path}/secret_scan")).collect()}
    mixed = after["source_mix"].doc_id.value_counts().to_dict()
    assert mixed == {k: v for k, v in want.items() if v}
    last = after["encode_pieces"]
    assert last.round_trip.all() and len(last) == sum(mixed.values())
    for folder in ("empty",):
        spark.createDataFrame([], SCHEMA).write.parquet(f"{tmp_path}/{folder}/documents.parquet")
        spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/{folder}/labels.parquet")
        assert corpus_pipeline.run(spark, f"{tmp_path}/{folder}").count() == 0
