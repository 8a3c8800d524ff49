"""Null ids, repeated rows and few labels in the training-data operators."""

from flowrings.llm import decontaminate, toxicity

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"


def test_stages_judge_rows(spark, tmp_path):
    import corpus_pipeline as p

    word = lambda i: "".join("aeioumnrst"[int(c)] for c in f"{i:05d}")
    text = lambda k: " ".join(word(k * 997 + i * 31) for i in range(30))
    bad = lambda k: text(k) + ". zzqgrubvile hateful. " + text(k + 50)
    bench = " ".join(f"bench{i}" for i in range(40))
    train = [(i, bad(i) if i % 2 else text(i)) for i in range(40)]
    cases = [(None, text(60)), (None, text(61)), (500, text(62)), (500, text(62)), (501, text(63)), (501, bad(64)), (502, text(65)), (502, "so " + bench), (None, text(66)), (400, text(66))]
    spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in train + cases], COLUMNS).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, i % 2) for i in range(40)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(0, bench)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for i, (_, stage) in enumerate(p.STAGES[:-1]):
        stage(spark, docs, str(tmp_path)).write.parquet(f"{tmp_path}/stage{i}")
        docs = spark.read.parquet(f"{tmp_path}/stage{i}")
    got = sorted(((r.doc_id, r.text) for r in docs.collect() if r.doc_id is None or r.doc_id >= 400), key=str)
    assert got == sorted([(None, text(60)), (None, text(61)), (500, text(62)), (501, text(63)), (502, text(65)), (400, text(66))], key=str)


def test_few_or_no_toxic_labels(spark, documents):
    clean = [f"plain words number {i} here. nothing else to say" for i in range(60)]
    toxic = [f"plain words number {i} here. zzqgrubvile hateful" for i in range(60, 66)]
    long = "nothing else to say here. " * 500
    docs = documents(clean + toxic + [long])
    labels = lambda ids: spark.createDataFrame([(i, int(i >= 60)) for i in ids], "doc_id long, toxic int")
    for ids, found in ((range(60), 0), (range(66), 1)):
        model = toxicity.train(docs, labels(ids))
        said = {r.doc_id: r.predicted for r in toxicity.score(docs, model).collect()}
        assert said[66] == 0 and not any(said[i] for i in range(60))
        assert all(said[i] == found for i in range(60, 66))


def test_decontaminate_paths_agree_on_null_and_repeated_ids(spark, documents):
    bench = " ".join(f"bench{i}" for i in range(20))
    docs = documents(["in " + bench, "clean", "a b c " * 9 + bench, "plain " * 30, None], [None, None, 7, 7, 8])
    items = spark.createDataFrame([(0, bench)], "item_id long, text string")
    by = [sorted(map(str, decontaminate.decontaminate(docs, items, **kw).collect())) for kw in ({}, {"broadcast_bytes": 0})]
    assert by[0] == by[1] and sum("contaminated=True" in r for r in by[0]) == 2


def test_stages_start_after_heaps_are_given_back(spark, documents):
    import corpus_pipeline as p

    docs, runtime = documents(["a b"]), spark._jvm.java.lang.Runtime.getRuntime()
    spark._jvm.System.gc()
    before = runtime.totalMemory()
    spark.range(0, 4, 1, 4).selectExpr("length(repeat(cast(id AS string), 250000000))").collect()  # an earlier stage's
    grown = runtime.totalMemory()
    assert grown > before + 200_000_000
    p.STAGES[-1][1](spark, docs, "")
    assert runtime.totalMemory() < grown - 200_000_000
