"""The pipeline stage by stage."""

import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")


def test_stages(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns, before = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf_dir).cache()
        assert docs.columns == columns, name
        if name != "mixing":
            assert 0 < docs.count() <= before
            before = docs.count()
            assert docs.select("doc_id").distinct().count() == before
    assert docs.groupBy("doc_id").count().agg({"count": "max"}).first()[0] <= 2
    last = corpus_pipeline.STAGES[-1][1](spark, docs, sf_dir)
    assert last.groupBy("sequence_id").agg({"length": "sum"}).agg({"sum(length)": "max"}).first()[0] <= 4096


def test_run(spark, sf_dir):
    rows = corpus_pipeline.run(spark, sf_dir).collect()
    assert rows and {r["doc_id"] for r in rows}


def test_odd_rows(spark, sf_dir):
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, "x y z", "en", None, 5), (3, "x y z", "en", None, 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for d in (docs, docs.limit(0)):
        for _, stage in corpus_pipeline.STAGES:
            d = stage(spark, d, sf_dir)
        d.collect()


def test_near_copies_by_five_words(spark, sf_dir):
    words = [f"w{i}" for i in range(200)]
    edited = [words[:i] + ["new"] + words[i + 1 :] for i in (20, 60, 100, 140)]
    far = [w if i % 20 else "other" for i, w in enumerate(words)]
    texts = [words, *edited, far, words]
    docs = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string")
    assert {r["doc_id"] for r in corpus_pipeline.drop_copies(spark, docs, sf_dir).collect()} == {0, 5}


def test_near_copies_by_brute_force(spark, sf_dir):
    from pivotjoin.llm import word_shingles

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    sets = {r["doc_id"]: frozenset(word_shingles.shingles(r["text"].encode()).tolist()) for r in docs.collect()}
    root = {i: i for i in sets}
    for i in sorted(sets):
        for j in sorted(sets):
            if i < j and root[i] != root[j] and 9 * len(sets[i] & sets[j]) >= 4 * (len(sets[i]) + len(sets[j])):
                a, b = sorted((root[i], root[j]))
                root = {k: a if v == b else v for k, v in root.items()}
    assert {r["doc_id"]: r["component_id"] for r in word_shingles.near_duplicates(docs).collect()} == root


def test_copies_come_from_fingerprints(spark, sf_dir, monkeypatch):
    from pivotjoin.llm import simhash, word_shingles

    words = [f"w{i}" for i in range(300)]
    edits = [" ".join([*words[:i], "new", *words[i + 1 :]]) for i in range(20, 280, 5)]
    bits = [(simhash.fingerprint(t.encode()) ^ simhash.fingerprint(" ".join(words).encode())).bit_count() for t in edits]
    near, far = (next(t for t, b in zip(edits, bits, strict=True) if f(b)) for f in (lambda b: 0 < b <= simhash.DISTANCE, lambda b: b > simhash.DISTANCE))
    repeated = "x y z " * 300  # equal fingerprints, other sets
    texts = [" ".join(words), near, far, repeated + "a b c d e f g", repeated + "h i j k l m n", " ".join(words).upper()]
    assert simhash.fingerprint(texts[3].encode()) == simhash.fingerprint(texts[4].encode())
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {r["doc_id"] for r in corpus_pipeline.drop_copies(spark, docs, sf_dir).collect()} == {0, 3, 4}
    real = word_shingles.near_links
    monkeypatch.setattr(word_shingles, "near_links", lambda posted, *a, **k: real(posted.limit(0), *a, **k))  # no bands
    assert {r["doc_id"] for r in corpus_pipeline.drop_copies(spark, docs, sf_dir).collect()} == {0, 2, 3, 4}
