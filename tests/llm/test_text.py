"""PII, URL lists, language, tokens, toxicity, decontamination, pipeline."""

import hashlib
import random
import re

import numpy as np
import pytest

from pyspark.sql import functions as F

from flowrings.llm import bpe, decontaminate, langid, pii, toxicity, url_filter

EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def plain_spans(text):
    out = [("email", *m.span()) for m in EMAIL.finditer(text)]
    out += [("ip", *m.span()) for m in IP.finditer(text) if all(int(p) <= 255 for p in m[0].split("."))]
    out += [("card", *m.span()) for m in CARD.finditer(text) if 12 <= len(re.sub(r"\D", "", m[0])) <= 19 and pii.luhn(re.sub(r"\D", "", m[0]))]
    return out + [("phone", *m.span()) for m in PHONE.finditer(text) if 9 <= len(re.sub(r"\D", "", m[0])) <= 15]


def test_base_spans_equal_plain_patterns():
    rng = random.Random(2)
    for _ in range(8000):
        text = "".join(rng.choice("0123456789.@a-+ ()%_é") for _ in range(rng.randrange(60)))
        assert sorted(pii.base_spans(text)) == sorted(plain_spans(text)), text


def test_checksums_and_context():
    assert pii.luhn("4111111111111111") and not pii.luhn("4111111111111112")
    assert pii.mod97("GB82WEST12345698765432") and not pii.mod97("GB82WEST12345698765431")
    assert pii.aba("021000021") and not pii.aba("021000022")
    kinds = lambda t: [x[0] for x in pii.find_spans(t)]
    assert kinds("iban GB82 WEST 1234 5698 7654 32 thanks") == ["iban"]
    assert kinds("my ssn is 123-45-6789") == ["ssn"] and kinds("order 123-45-6789") == []
    assert kinds("routing 021000021") == ["routing"] and kinds("code 021000021") == []
    assert pii.mask("mail a@b.co now", pii.find_spans("mail a@b.co now")) == "mail <email> now"


def test_secrets_need_entropy_and_context():
    kinds = lambda t: [x[0] for x in pii.find_spans(t)]
    key = "04dbebab91ab85687d33eeaaf9ac699e1188f962"
    assert kinds(f'token = "{key}"') == ["secret"] and kinds(f"commit {key}") == [] and kinds(f"see {key}") == []
    assert kinds("password: " + "a" * 40) == [] and kinds("api_key=") == [] and kinds("secret " + "x1" * 20_000) == []
    assert pii.mask(f"key token {key} end", pii.find_spans(f"key token {key} end")) == "key token <secret> end"


def test_pii_digest_and_counts(documents, prose):
    """base_sha256 and the counts against plain patterns, on rows with null, repeated and very long texts."""
    order = ("email", "ip", "card", "phone")
    texts = [*prose[:20], "a@b.co é 10.0.0.1 4111 1111 1111 1111 call +44 20 7946 0958, 300.1.1.1", "a@b.co " * 9000, None, "", "1.2.3.4.5.6.7.8 x@y.z@q.r"]
    ids = [*range(len(texts) - 1), 3]
    got = sorted((r.doc_id, r.n_email, r.n_ip, r.n_card, r.n_phone, r.base_sha256) for r in pii.detect(documents(texts, ids)).collect())
    want = []
    for i, t in zip(ids, texts):
        spans = sorted(plain_spans(t or ""), key=lambda x: (x[1], order.index(x[0])))
        want.append((i, *(sum(x[0] == k for x in spans) for k in order), hashlib.sha256(",".join(f"{k}:{s}:{e}" for k, s, e in spans).encode()).hexdigest()))
    assert got == sorted(want)
    assert pii.detect(documents(["x"]).limit(0)).count() == 0


def test_pii_rows(documents):
    got = {r.doc_id: r for r in pii.detect(documents([None, "", "ß a@b.co +1 555 123 4567", "9" * 5000])).collect()}
    assert got[0].spans == got[1].spans == got[3].spans == ""
    assert got[2].spans == "email:2:8,phone:9:24" and (got[2].n_email, got[2].n_phone) == (1, 1)


def test_url_list_follows_time(spark):
    entries = spark.sql("""SELECT list_name, key, verdict, event, CAST(day AS DATE) AS day FROM VALUES
        ('a', 'bad.com', 'block', 'add', '2024-02-01'), ('a', 'bad.com', 'block', 'remove', '2024-03-01'), ('a', 'bad.com', 'block', 'add', '2024-05-01'),
        ('b', 'x.bad.com/ok', 'allow', 'add', '2024-01-01'), ('c', NULL, 'block', 'add', '2024-01-01') AS t(list_name, key, verdict, event, day)""")
    rows = [(1, "http://bad.com/p", "2024-01-31"), (2, "http://X.Bad.com./p", "2024-02-01"), (3, "https://u@bad.com:80/", "2024-03-01"), (4, "//x.bad.com/ok/y?z", "2024-06-01"), (5, None, "2024-06-01"), (6, "bad.com", "2024-06-01"), (7, "http://bad.com", None), (8, "http://verybad.com", "2024-06-01"), (9, "http://x.bad.com/okay", "2024-06-01")]
    caps = spark.createDataFrame(rows, "page_id long, url string, fetched string").selectExpr("page_id", "url", "cast(fetched as date) fetched", "'k' key", "1 n_hits")
    got = {r.page_id: (r.n_hits, r.blocked) for r in url_filter.judge(caps, entries).collect()}
    assert got == {1: (0, False), 2: (1, True), 3: (0, False), 4: (2, False), 5: (0, False), 6: (0, False), 7: (0, False), 8: (0, False), 9: (1, True)}
    assert url_filter.judge(caps.limit(0), entries).count() == 0 and url_filter.judge(caps, entries.limit(0)).filter("n_hits > 0").count() == 0


def test_url_paths_keep_their_case_and_captures_their_day(spark):
    entries = spark.sql("""SELECT list_name, key, verdict, event, CAST(day AS DATE) AS day FROM VALUES
        ('a', 'Ex.COM/Path', 'block', 'add', '2024-02-01'), ('b', 'ex.com', 'allow', 'add', '2024-01-01'), ('b', 'ex.com', 'allow', 'remove', '2024-06-01'),
        ('b', 'ex.com', 'allow', 'add', '2024-08-01'), ('b', 'ex.com', 'allow', 'add', '2024-08-01') AS t(list_name, key, verdict, event, day)""")
    rows = [(1, "http://EX.com/Path/x", "2024-03-01"), (1, "http://ex.com/path", "2024-03-01"), (1, "http://ex.com/Path", "2024-01-15"), (1, "http://ex.com/Path", "2024-07-01"),
            (None, "http://ex.com/Path", "2024-09-01"), (2, "http://ex.com/Path", "2024-09-01"), (2, "http://ex.com/Path", "2024-09-01"), (3, "", None), (4, "http://" + "a." * 50 + "ex.com/" + "p/" * 2000, "2024-03-01")]
    caps = spark.createDataFrame(rows, "page_id long, url string, fetched string").selectExpr("page_id", "url", "cast(fetched as date) fetched", "1 spans", "'q' hit_url")
    got = sorted(((r.page_id or 0), r.n_hits, r.matched, r.blocked) for r in url_filter.judge(caps, entries).collect())
    both, b = (2, "a:ex.com/Path,b:ex.com", True), (1, "b:ex.com", False)
    assert got == sorted([(1, *both), (1, *b), (1, *b), (1, 1, "a:ex.com/Path", True), (0, *both), (2, *both), (2, *both), (3, 0, "", False), (4, *b)])
    changes = [("a", "hot.com", "block", ("add", "remove")[i % 2], f"2024-{1 + i // 28:02d}-{1 + i % 28:02d}") for i in range(200)]
    many = spark.createDataFrame(changes, "list_name string, key string, verdict string, event string, day string").withColumn("day", F.col("day").cast("date"))
    asked = spark.range(200).selectExpr("id AS page_id", "'http://hot.com/' AS url", "make_date(2024, cast(1 + id div 28 as int), cast(1 + id % 28 as int)) AS fetched")
    assert {r.page_id: r.n_hits for r in url_filter.judge(asked, many).collect()} == {i: 1 - i % 2 for i in range(200)}


def test_tokens_equal_the_library(documents):
    from tokenizers import Tokenizer

    path, rng = bpe.default_vocabulary(), random.Random(1)
    lib, own = Tokenizer.from_file(path), bpe.WordTrie(path, 500)
    texts = ["Hello World's 12 été <|endoftext|> x", "", "İΣ ΑΣ ﬁ 中文 á", "<|STARTOFTEXT|><|startoftext|>", "=-" * 60, "haha" * 50, "\x1c\x1da\x85b\xa0c"]
    texts += ["".join(chr(rng.choice([rng.randrange(32, 127), rng.randrange(0, 600), rng.randrange(0x300, 0x3000)])) for _ in range(rng.randrange(60))) for _ in range(400)]
    texts += [" ".join("".join(rng.choice("aeinrstlhod") for _ in range(rng.randrange(1, 16))) for _ in range(20)) for _ in range(200)]
    for i in range(0, len(texts), 50):
        for text, (ids, decoded) in zip(texts[i : i + 50], own.encode_batch(texts[i : i + 50])):
            want = lib.encode(text, add_special_tokens=False).ids
            assert ids == " ".join(map(str, want)), text
            assert decoded == lib.decode(want, skip_special_tokens=False) == own.decode(want)
    got = {r.doc_id: (r.n_tokens, r.ids) for r in bpe.encode_documents(documents([None, "", texts[0]]), path).collect()}
    assert got == {0: (0, []), 1: (0, []), 2: (9, lib.encode(texts[0], add_special_tokens=False).ids)}


def labelled(spark, n=400):
    rng = random.Random(4)
    word = lambda: "".join(rng.choice(["an", "er", "th", "on", "ing", "ed"]) for _ in range(rng.randrange(1, 4)))
    rows, labels = [], []
    for i in range(n):
        sentences = [" ".join(word() for _ in range(8)) for _ in range(rng.randrange(1, 6))]
        toxic = int(i % 4 == 0)
        if toxic:
            sentences[rng.randrange(len(sentences))] += f" you {rng.choice(['idiot', 'moron', 'scumbag'])}"
        rows.append((i, ". ".join(sentences) + "."))
        labels.append((i, toxic))
    return spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")


def test_toxicity_learns_and_locates(spark, documents):
    docs, labels = labelled(spark)
    model = toxicity.train(docs, labels)
    got = toxicity.score(docs, model).join(labels, "doc_id").withColumn("held", toxicity.held_out()).filter("held").collect()
    assert len(got) > 50 and sum(r.predicted == r.toxic for r in got) / len(got) > 0.95
    worst = [r.worst for r in got if r.toxic and r.predicted]
    assert sum(any(w in x for w in ("idiot", "moron", "scumbag")) for x in worst) / len(worst) > 0.9
    odd = {r.doc_id: (r.score, r.predicted) for r in toxicity.score(documents([None, "", " . ", "x" * 100_000]), model).collect()}
    assert odd[0] == odd[1] == (0.0, 0) and odd[3][1] == 0
    assert toxicity.score(documents(["a"]), toxicity.train(docs, labels.limit(0))).first().predicted == 0
    assert toxicity.train(docs, labels).bias == model.bias


def test_sentences_are_numbered_alike():
    text = "One two. Three idiot four! Five?\nsix"
    f, where, n = toxicity.features(text)
    assert n == len(toxicity.sentences(text)) and "idiot" in toxicity.sentences(text)[1]
    assert set(where.tolist()) <= set(range(n))


def test_language(spark, documents):
    rng = random.Random(9)
    parts = {"en": ["the", "ing", "tion", "wh"], "de": ["sch", "ung", "ä", "ch"], "es": ["ción", "ñ", "ll", "que"]}
    rows = [(i, " ".join("".join(rng.choice(parts[k]) for _ in range(3)) for _ in range(12)), k) for i in range(300) for k in [list(parts)[i % 3]]]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.train(docs, sample=150)
    got = langid.predict(docs, model).join(docs, "doc_id").collect()
    assert sum(r.lang == r.lang_pred for r in got) / len(got) > 0.98 and all(0 <= r.score <= 1 for r in got)
    odd = {r.doc_id: (r.lang_pred, r.score) for r in langid.predict(documents([None, "", "12 34 !", "the"]), model).collect()}
    assert odd[0] == odd[1] == odd[2] == ("und", 0.0) and odd[3][0] == "en"
    assert langid.predict(docs, langid.train(docs.limit(0))).first().lang_pred == "und"


def test_language_sample_is_dealt_by_language(spark):
    """A language of one document in 500 is learned, repeated rows do not flood the sample, columns may be named otherwise."""
    rng = random.Random(3)
    parts = {"en": ["the", "ing", "tion"], "xx": ["qzq", "vvk", "zzk"]}
    say = lambda k: " ".join("".join(rng.choice(parts[k]) for _ in range(3)) for _ in range(8))
    rows = [(i, say("xx" if i % 250 == 0 else "en"), "xx" if i % 250 == 0 else "en") for i in range(2500)] + [(9, "the the the", "en")] * 2000 + [(None, "x", "yy")]
    docs = spark.createDataFrame(rows, "key long, body string, said string").selectExpr("key", "body", "said", "'z' AS lang", "1 AS doc_id", "'t' AS text")
    model = langid.train(docs, sample=200, least=5, id_col="key", text_col="body", lang_col="said")
    assert model.classes == ["en", "xx"]
    got = langid.predict(docs, model, "key", "body").join(docs.selectExpr("key AS doc_id", "said").distinct(), "doc_id").filter("said = 'xx'").collect()
    assert len(got) == 10 and all(r.lang_pred == "xx" for r in got)
    assert langid.quotas({"a": 10_000, "b": 7, "c": 300}, 1000, 40) == {"a": 970, "b": 7, "c": 40}
    tie = langid.LanguageModel(model.idf, np.zeros((1 << langid.BITS, 2)), np.zeros(2), ["a", "b"])
    assert tie.predict("text") == ("a", 0.5)


def plain_ftrl(rows, n_classes, epochs, alpha, beta, l1, l2):
    """The same steps with dictionaries, one coordinate at a time."""
    z, n = {}, {}

    def weight(j, c):
        x = z.get((j, c), 0.0)
        keep = abs(x) if j == "bias" else max(abs(x) - l1, 0.0)
        return -(keep if x > 0 else -keep) / ((beta + n.get((j, c), 0.0) ** 0.5) / alpha + l2)

    for _ in range(epochs):
        for at, x, y in rows:
            feats = [*zip(at.tolist(), x.tolist()), ("bias", 1.0)]
            w = {(j, c): weight(j, c) for j, _ in feats for c in range(n_classes)}
            s = [sum(v * w[j, c] for j, v in feats) for c in range(n_classes)]
            e = [np.exp(t - max(s)) for t in s]
            for j, v in feats:
                for c in range(n_classes):
                    g = v * (e[c] / sum(e) - (c == y))
                    old = n.get((j, c), 0.0)
                    n[j, c] = old + g * g
                    z[j, c] = z.get((j, c), 0.0) + g - (n[j, c] ** 0.5 - old**0.5) / alpha * w[j, c]
    return weight


def test_ftrl_equals_plain_loops():
    rng = np.random.default_rng(2)
    rows = [(np.sort(rng.choice(30, 6, replace=False)), rng.uniform(0.1, 1, 6), int(rng.integers(3))) for _ in range(50)]
    w, bias = langid.ftrl(rows, 3, epochs=2, alpha=0.5, beta=1.0, l1=0.3, l2=0.01)
    weight = plain_ftrl(rows, 3, 2, 0.5, 1.0, 0.3, 0.01)
    assert w[:30] == pytest.approx(np.array([[weight(j, c) for c in range(3)] for j in range(30)]))
    assert bias == pytest.approx([weight("bias", c) for c in range(3)])
    assert (w[30:] == 0).all() and (w[:30] == 0).any() and (w[:30] != 0).any()


def test_temperature_is_the_best_of_a_grid():
    rng = np.random.default_rng(4)
    y = rng.integers(0, 3, 400)
    logits = rng.normal(0, 1, (400, 3)) * 6
    logits[np.arange(400), y] += 4

    def loss(t):
        z = logits / t
        return float((np.log(np.exp(z - z.max(axis=1, keepdims=True)).sum(axis=1)) + z.max(axis=1) - z[np.arange(400), y]).mean())

    best = langid.fit_temperature(logits, y)
    assert best > 1.2 and all(loss(best) <= loss(t) + 1e-9 for t in np.exp(np.linspace(-2.9, 2.9, 200)))
    assert langid.fit_temperature(np.empty((0, 3)), np.empty(0, int)) == 1.0


def noisy_or_loss(bags, w, bias, l2):
    """Negative log likelihood of the labels a document, sentence by sentence, and the penalty."""
    total = 0.0
    for label, n, where, f in bags:
        z = [bias + sum(w[k] for i, k in zip(where, f) if i == s) for s in range(n)]
        none = np.prod([1 - 1 / (1 + np.exp(-t)) for t in z])
        total -= np.log(1 - none) if label else np.log(none)
    return total / len(bags) + l2 * (w**2).sum() / 2 / len(bags)


def test_noisy_or_fit_is_a_minimum():
    """Dense and one-class documents: no small step from the fitted weights lowers the loss by much."""
    rng = np.random.default_rng(7)
    bags = []
    for i in range(60):
        n, m = int(rng.integers(1, 5)), 6
        where, f = np.sort(rng.integers(0, n, m)).astype(np.int32), rng.integers(1, 5, m).astype(np.int32)
        if label := int(i % 3 == 0):
            f[0] = 0
        bags.append((label, n, where, f))
    w, bias = toxicity._fit(bags, 5, l2=0.5, steps=3000, rate=0.02)
    loss = lambda w, b: noisy_or_loss(bags, w, b, 0.5)
    at, step = loss(w, bias), 1e-4
    slopes = [(loss(w + step * e, bias) - loss(w - step * e, bias)) / (2 * step) for e in np.eye(5)] + [(loss(w, bias + step) - loss(w, bias - step)) / (2 * step)]
    assert max(map(abs, slopes)) < 1e-3 and at < loss(np.zeros(5), -2.0) and w[0] > 2 > max(w[1:])
    p = np.array([0.1, 0.5, 0.2])
    assert toxicity.noisy_or(p) == pytest.approx(1 - np.prod(1 - p)) and toxicity.noisy_or(np.empty(0)) == 0.0


def test_empty_tables_and_repeated_rows(spark, documents):
    """Row by row operators give a row for each input row, whatever its id, and none for an empty table."""
    docs, labels = labelled(spark, 80)
    lang = documents(["the thing", "the other"], [1, 2]).withColumn("lang", F.lit("en"))
    bench = spark.createDataFrame([("q", "one two three")], "item_id string, text string")
    odd = documents(["one two three", None, "one two three", "x " * 60_000], [None, 5, 5, 5])
    tox, words = toxicity.train(docs, labels), langid.train(lang)
    for run in (lambda d: langid.predict(d, words), lambda d: toxicity.score(d, tox), lambda d: bpe.encode_documents(d, bpe.default_vocabulary()), lambda d: decontaminate.decontaminate(d, bench)):
        assert run(odd.limit(0)).count() == 0
        got = run(odd).collect()
        assert sorted(str(r.doc_id) for r in got) == ["5", "5", "5", "None"]
        assert len({str(r.asDict() | {"doc_id": 0}) for r in got}) <= 3  # equal texts, equal results
    assert toxicity.train(docs.limit(0), labels).bias == toxicity.NO_EVIDENCE and langid.train(lang.limit(0)).classes == []
    columns = docs.withColumn("keep", F.lit(1)).withColumn("score", F.lit("a")).columns
    kept = toxicity.keep_harmless(docs.withColumn("keep", F.lit(1)).withColumn("score", F.lit("a")), tox)
    assert kept.columns == columns and 40 < kept.count() < 80


def words_of(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)


def brute_hits(docs, items):
    out = {}
    for i, t in enumerate(docs):
        w, hit, found = words_of(t), set(), set()
        for name, text in items:
            x = words_of(text)
            n = min(13, len(x))
            windows = {tuple(x[j : j + n]) for j in range(len(x) - n + 1)} if n else set()
            for j in range(len(w) - n + 1):
                if n and tuple(w[j : j + n]) in windows:
                    hit.update(range(j, j + n))
                    found.add(name)
        out[i] = (len(w), len(hit), len(found), bool(hit) and 20 * len(hit) >= len(w))
    return out


@pytest.mark.parametrize("limit", [1 << 25, 0])
def test_decontamination(spark, documents, prose, limit):
    items = [("q1", prose[0]), ("q2", "x y"), ("q3", None), ("q4", " ".join(prose[9].split()[2:30])), ("q5", "an er th on ing"), ("q6", prose[50]), ("q7", "!!"), ("q8", "x")]
    texts = prose + ["X, y!", "Ä x y z", prose[0].upper() + " more words " * 200, "--"]
    bench = spark.createDataFrame(items, "item_id string, text string")
    judged = decontaminate.decontaminate(documents(texts), bench, broadcast_bytes=limit).collect()
    assert {r.doc_id: (r.n_words, r.n_hit, r.n_items, r.contaminated) for r in judged} == brute_hits(texts, items)
    clean = decontaminate.keep_clean(documents(texts), bench, broadcast_bytes=limit)
    assert clean.columns == documents(texts).columns and sorted(r.doc_id for r in clean.collect()) == sorted(r.doc_id for r in judged if not r.contaminated)
    assert decontaminate.decontaminate(documents(texts), bench.limit(0), broadcast_bytes=limit).filter("n_hit > 0").count() == 0
    assert decontaminate.decontaminate(documents(texts).limit(0), bench, broadcast_bytes=limit).count() == 0


def test_pipeline_stages(spark, documents, tmp_path):
    import corpus_pipeline as p

    docs, labels = labelled(spark, 240)
    rows = [(r.doc_id, r.text, "en", "s", len(r.text)) for r in docs.collect()]
    bench = " ".join(f"bench{i}" for i in range(40))
    rows += [(1000, rows[1][1], "en", "s", 1), (1001, "before " + bench + " after", "en", "s", 1), (1002, None, "en", "s", 0)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(0, bench)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    columns, kept = docs.columns, []
    for i, (_, stage) in enumerate(p.STAGES):
        out = stage(spark, docs, str(tmp_path))
        assert i == len(p.STAGES) - 1 or out.columns == columns
        out.write.parquet(f"{tmp_path}/stage{i}")
        docs = spark.read.parquet(f"{tmp_path}/stage{i}")
        kept.append({r.doc_id for r in docs.select("doc_id").collect()})
    assert all(b <= a for a, b in zip(kept, kept[1:]))
    assert 1 not in kept[1] and 1000 in kept[1] and 1001 in kept[2] and 1001 not in kept[3] and len(kept[4]) > 100
    assert {r.doc_id for r in p.run(spark, str(tmp_path)).select("doc_id").collect()} == kept[4]
