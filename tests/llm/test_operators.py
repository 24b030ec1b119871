"""The training-data operators against brute force, exact round trips, held-out accuracy, and odd rows."""

import hashlib
import random
import zlib

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from rankspark.llm import ann, bpe, chat, common, decontamination, gbdt, langid, licenses, neardup, quality, queries, sharding, toxicity
from rankspark.llm.common import table

DATA, MIDDLE = "/root/testdata/sf0.001", "/root/testdata/sf0.01"
DOC = "doc_id long, text string, lang string, source string, n_chars long, score double, rep long, c long"
LABELS = "doc_id long, quality int, toxic int, text string"


@pytest.fixture(scope="module")
def odd(spark):
    """Null and empty texts, a long one, copies, a repeated row, a null id, and columns whose names clash."""
    long = " ".join(f"w{i}" for i in range(20_000))
    texts = [None, "", " \n", "one", "One two", "one two", "one two", long, long + " end", "Σ ΟΔΟΣ É", "MIT License mit LICENSE", "!!! ..."]
    rows = [(i, t, None if i % 3 else "en", "s", 0, 1.0, 5, 6) for i, t in enumerate(texts)]
    return spark.createDataFrame([*rows, rows[5], (None, "one two", "fr", None, None, 0.0, 1, 1)], DOC)


def against_sql(spark, name, data=MIDDLE):
    db = duckdb.connect()
    for t in ("documents", "benchmark", "conversations"):
        db.execute(f"create view {t} as select * from '{data}/{t}.parquet'")
    df = queries.QUERIES[name](spark, data)
    columns = sorted(df.columns)
    told = db.execute(queries.SQL[name])
    names = [d[0] for d in told.description]
    assert sorted(names) == columns
    canon = lambda v: round(v, 9) if isinstance(v, float) else v
    assert sorted((tuple(canon(r[c]) for c in columns) for r in df.collect()), key=str) == sorted((tuple(canon(r[names.index(c)]) for c in columns) for r in told.fetchall()), key=str)


@pytest.mark.parametrize("name", sorted(queries.SQL))
def test_equal_to_sql(spark, name):
    against_sql(spark, name)


def test_odd_rows_everywhere(spark, odd):
    n = odd.count()
    empty, labels = odd.where("false"), spark.createDataFrame([(i, i % 2, i % 2, "x") for i in range(12)], LABELS)
    bench = spark.createDataFrame([(1, "one two", 1.0), (1, "one two", 1.0), (2, None, 0.0), (None, "one", 0.0), (3, " ".join(f"w{i}" for i in range(30, 55)), 1.0)], "item_id long, text string, doc_id double")
    model = langid.train(odd)
    for docs, rows in ((odd, n), (empty, 0)):
        assert toxicity.score(docs, labels).count() == rows and quality.score(docs, labels).count() == rows
        assert langid.predict(docs, model).count() == rows and licenses.scan(docs).count() == rows
        assert sharding.assign(docs).count() == rows and neardup.group(docs, 2).count() == rows
        assert decontamination.report(docs, bench).count() == rows and decontamination.report(docs, bench.where("false")).where("contaminated").count() == 0
        assert bpe.encoded(docs, _path()).count() == rows
    assert {r["lang_pred"] for r in langid.predict(odd.where("doc_id in (0, 1, 2, 11)"), model).collect()} == {"und"}
    seen = {r["doc_id"]: r for r in decontamination.report(odd, bench).collect()}
    assert (seen[5]["n_hit"], seen[5]["n_items"], seen[7]["n_hit"], seen[0]["n_hit"]) == (2, 1, 25, 0)
    found = {r["doc_id"]: r for r in licenses.scan(odd).collect()}
    assert (found[10]["n_base"], found[10]["first_word"], found[10]["last_word"], found[10]["base_labels"], found[0]["n_words"]) == (2, 0, 2, "mit", 0)
    groups = {r["doc_id"]: r for r in neardup.group(odd, 2).collect()}
    assert groups[4]["component_id"] == groups[5]["component_id"] == groups[6]["component_id"] == 4 and groups[8]["component_id"] == 7 and groups[1]["kept"]


def _path():
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def test_bpe_equals_library():
    from tokenizers import Tokenizer

    told, codec, rnd = Tokenizer.from_file(_path()), bpe.Codec(open(_path(), encoding="utf-8").read()), random.Random(3)
    texts = ["", " ", "a<|endoftext|>b", "x</w>y <|startoftext|>", "Don't we'LL 'S", "ΣΑΣ Σ", "İstanbul ẞ", "日本語 한국어", "a" * 700, "👩‍👧 ½²³ ４５", "\x00\x85​", "…—“”" * 9]
    texts += ["".join(rnd.choice("etaoinshrdlu"[: rnd.choice([3, 12])]) for _ in range(rnd.randint(1, 30))) for _ in range(1500)]
    texts += ["".join(chr(rnd.choice([rnd.randint(32, 127), rnd.randint(128, 1000), rnd.randint(0x3000, 0x9000)])) for _ in range(9)) for _ in range(500)]
    texts += [f"a{chr(c)}b{chr(c)}\u0307 {chr(c)}1" for c in [0x558, 0x88F, 0x1C89, 0x1C8A, 0x209D, 0xA7CB, 0xA7DC, 0xA7DD, 0x105C9, 0x105D2, 0x10940, 0x10D50, 0x113C2, *range(0x700, 0x11000, 97)] if not 0xD800 <= c < 0xE000]
    for t in texts:
        want = told.encode(t, add_special_tokens=False).ids
        got = np.frombuffer(codec.encode(t), dtype="<u4")
        assert got.tolist() == want and codec.decode(got).decode() == told.decode(want, skip_special_tokens=False)


def test_worker_keeps_one_owner():
    batch = pa.record_batch({"x": [1, 2, 3]})
    first = common.held("a", lambda: [1])
    assert common.held("a", lambda: [2]) is first and [b.num_rows for b in common.slices(iter([batch]), 2, "a")] == [2, 1]
    assert common.held("a", lambda: [3]) is first
    assert [b.num_rows for b in common.slices(iter([batch]), 2)] == [2, 1]
    assert common.held("a", lambda: [4]) == [4] and common.held("b", lambda: [5]) == [5] and common.held("a", lambda: [6]) == [6]


def test_bpe_query_digests(spark):
    from tokenizers import Tokenizer

    told = Tokenizer.from_file(_path())
    texts = {r["doc_id"]: r["text"] for r in table(spark, DATA, "documents").collect()}
    for r in queries.tokenized(spark, DATA).collect():
        ids = told.encode(texts[r["doc_id"]], add_special_tokens=False).ids
        assert r["n_tokens"] == len(ids) and r["ids_sha256"] == hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(told.decode(ids, skip_special_tokens=False).encode()).hexdigest()


def test_chat_round_trip_and_language():
    rnd = random.Random(5)
    for _ in range(400):
        turns = [{"role": rnd.choice(["user", "assistant", "a&b\nc", "<|im_end|>"]), "text": "".join(rnd.choice(["<", "|", "\\", "<|im_end|>", "<|im_start|>", "\n", "&nl;", "x"]) for _ in range(rnd.randint(0, 9)))} for _ in range(rnd.randint(0, 4))]
        out, spans = chat.render(turns)
        assert list(chat.Reader().feed(out)) == [(t["role"], t["text"]) for t in turns]
        assert [chat.unescape(out[a:z]) for a, z in spans] == [t["text"] for t in turns if t["role"] == "assistant"]
    run = lambda source, **scope: (lambda out: (chat.compile_template(source)(scope, lambda p, m: out.append(p)), "".join(out))[1])([])
    assert run("{{ 'a' + 'b' | upper }}{% if 1 == 2 %}no{% elif x and not y %}yes{% else %}?{% endif %}", x=1, y=0) == "aByes"
    assert chat.fold(chat.parse("a{{ 'b' + 'c' }}{% if false %}{{ x }}{% endif %}d"))[1] == [("emit", ("constant", "abcd"))]
    for bad in ("{{ x.__class__() }}", "{% import os %}", "{{ x | eval }}", "{% for a in b %}", "{{ 'a }}"):
        with pytest.raises(chat.TemplateError):
            chat.compile_template(bad)


def test_sharding_law(spark):
    docs = table(spark, MIDDLE, "documents")
    rows = sharding.assign(docs, ranges=37).collect()
    texts = {r["doc_id"]: r["text"].encode() for r in docs.collect()}
    assert all(r["size"] == len(texts[r["doc_id"]]) + 1 and r["text_crc32"] == zlib.crc32(texts[r["doc_id"]]) for r in rows)
    by = {s: [r for r in rows if r["shard"] == s] for s in range(16)}
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1 and all(sorted(r["slot"] for r in x) == list(range(len(x))) for x in by.values())
    share = [sum(r["source"] == "src3" for r in x) for x in by.values()]
    assert max(share) - min(share) <= 2
    assert {(r["doc_id"], r["shard"], r["slot"]) for r in rows} == {(r["doc_id"], r["shard"], r["slot"]) for r in sharding.assign(docs, ranges=16).collect()}


def test_super_minhash_is_unbiased_and_sharper():
    rng = np.random.default_rng(0)
    a = [rng.integers(0, 2**63, 60).astype(np.uint64) for _ in range(400)]
    b = [np.concatenate([s[:48], rng.integers(0, 2**63, 12).astype(np.uint64)]) for s in a]
    same = (neardup.signatures(a) == neardup.signatures(b)).mean(axis=1)
    true = 48 / 72
    assert abs(same.mean() - true) < 0.01 and same.std() < (true * (1 - true) / 128) ** 0.5
    assert (neardup.signatures(a[:3]) == np.vstack([neardup.signatures([s[::-1]]) for s in a[:3]])).all()


def test_parity_bits_never_outnumber_differences():
    rng = np.random.default_rng(1)
    for _ in range(50):
        x, y = (np.unique(rng.integers(0, 900, rng.integers(1, 600)).astype(np.uint64)) for _ in range(2))
        bits = neardup.parities([x, y]).view(np.uint64)
        assert sum(int(v).bit_count() for v in bits[0] ^ bits[1]) <= len(np.setxor1d(x, y))


def test_shingles_of_pieces():
    text, size = "ab\tcd  ef gh " * 40, neardup.PIECE
    whole = neardup.shingle_sets([text, None, "x"], 2)
    try:
        neardup.PIECE = 17
        cut = neardup.shingle_sets([text, None, "x"], 2)
    finally:
        neardup.PIECE = size
    assert all((p == q).all() for p, q in zip(whole, cut, strict=True)) and list(map(len, whole)) == [4, 0, 1]


def test_components(spark):
    rng = np.random.default_rng(2)
    pairs = [(int(a), int(b)) for a, b in rng.integers(0, 300, (220, 2))] + [(i, i + 1) for i in range(1000, 1060)]
    root = {}

    def find(x):
        while root.get(x, x) != x:
            x = root[x]
        return x

    for a, b in pairs:
        lo, hi = sorted((find(a), find(b)))
        root[hi] = lo
    got = {r["v"]: r["component"] for r in neardup.components(spark.createDataFrame(pairs, "u long, v long")).collect()}
    assert got == {x: find(x) for p in pairs if p[0] != p[1] for x in p}


def test_neighbours_recall(spark):
    rows = queries.neighbours(spark, "/root/testdata/sf0.1").collect()
    data = sorted((r["vec_id"], r["embedding"]) for r in table(spark, "/root/testdata/sf0.1", "embeddings").collect())
    ids, x = np.array([i for i, _ in data]), np.array([v for _, v in data], dtype=np.float64)
    found = total = 0
    for q in ids[ids % 100 == 0]:
        d = np.sqrt(((x - x[ids == q]) ** 2).sum(axis=1))
        d[ids == q] = np.inf
        got = {r["vec_id"]: r for r in rows if r["query_id"] == q}
        assert sorted(r["rank"] for r in got.values()) == list(range(1, 11)) and all(r["score"] == pytest.approx(d[ids == v][0], abs=1e-12) for v, r in got.items())
        found, total = found + len(set(ids[np.lexsort((ids, d))[:10]].tolist()) & set(got)), total + 10
    assert found / total >= 0.9


def test_neighbours_of_groups_finer_than_the_codes(spark):
    """Queries lie in a group far tighter than the codebooks tell apart, and among vectors of many scales."""
    rng = np.random.default_rng(4)
    ids, wide = np.arange(6000), rng.normal(size=(6000, 24))
    tight = np.where(ids[:, None] % 10 == 0, 3 + 1e-4 * wide, 5 * rng.normal(size=(6000, 24)))
    scales = wide * 10.0 ** rng.uniform(-10, 10, size=(6000, 1))
    for x in (tight, scales):
        data = spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(ids, x, strict=True)], "vec_id long, embedding array<double>")
        got = {}
        for r in ann.search(data, F.col("vec_id") % 100 == 0).collect():
            got.setdefault(r["query_id"], set()).add(r["vec_id"])
        found = 0
        for q in ids[::100]:
            d = np.sqrt(((x - x[q]) ** 2).sum(axis=1))
            d[q] = np.inf
            found += len(set(np.lexsort((ids, d))[:10].tolist()) & got[int(q)])
        assert found / 600 >= 0.95


def test_neighbours_odd_vectors(spark):
    rows = [(0, [1.0, 0.0]), (1, None), (2, [0.0, 0.0]), (3, [None, 1.0]), (4, [float("nan"), 1.0]), (5, [float("inf"), 1.0]), (6, [1.0, 0.0]), (7, [1.0, 0.0]), (8, [0.0, 2.0]), (None, [1.0, 1.0]), (9, [1.0])]
    got = ann.search(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), F.col("vec_id") % 100 == 0, 10)
    assert [(r["vec_id"], r["score"]) for r in got.orderBy("rank").collect()] == [(6, 0.0), (7, 0.0), (8, pytest.approx(5**0.5))]
    assert ann.search(spark.createDataFrame([], "vec_id long, embedding array<float>"), F.col("vec_id") % 100 == 0).count() == 0


def test_held_out_accuracy(spark):
    data = "/root/testdata/sf0.1"
    labels = table(spark, data, "labels")
    for name, label, least in (("op1_toxicity", "toxic", 0.97), ("op5_quality", "quality", 0.97)):
        met = queries.QUERIES[name](spark, data).where("held_out").join(labels, "doc_id").agg(F.avg((F.col("predicted") == F.col(label)).cast("int"))).first()[0]
        assert met >= least
    docs = table(spark, data, "documents").select("doc_id", "lang")
    assert queries.language(spark, data).where("held_out").join(docs, "doc_id").agg(F.avg((F.col("lang_pred") == F.col("lang")).cast("int"))).first()[0] >= 0.98


def test_trees_and_isotonic():
    rng = np.random.default_rng(4)
    x = rng.normal(size=(3000, 5))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.5)).astype(float)
    m = gbdt.fit(x[:2000], y[:2000])
    assert ((m.probability(x[2000:]) > 0.5) == y[2000:]).mean() > 0.95
    one = [gbdt.Trees(m.feature[:k], m.threshold[:k], m.leaf[:k], m.base).margin(x[:1])[0] for k in (0, len(m.leaf))]
    assert one[0] == m.base and one[1] == pytest.approx(m.margin(x[:5])[0])
    knots, values = gbdt.isotonic(rng.random(500), rng.integers(0, 2, 500).astype(float))
    assert (np.diff(values) > 0).all() and (np.diff(knots) > 0).all()
    assert gbdt.fit(np.zeros((0, 3)), np.zeros(0)).probability(np.zeros((2, 3))).tolist() == [0.5, 0.5]


def test_pipeline_stages(spark):
    import corpus_pipeline

    docs, kept = table(spark, DATA, "documents"), []
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, DATA).cache()
        assert docs.columns == columns
        kept.append((name, {r["doc_id"] for r in docs.select("doc_id").collect()}))
    texts = {r["doc_id"]: r["text"] for r in table(spark, DATA, "documents").collect()}
    sets = {i: set(zip(*[texts[i].lower().split()[j:] for j in range(5)], strict=False)) for i in kept[1][1]}
    ids, parent = sorted(sets), {i: i for i in sets}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a in ids:
        for b in ids:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                lo, hi = sorted((find(a), find(b)))
                parent[hi] = lo
    same = {}
    for i in ids:  # texts under five words are one shingle
        if not sets[i] and texts[i].split():
            same.setdefault(tuple(texts[i].lower().split()), i)
    assert kept[2][1] == {i for i in ids if find(i) == i and (sets[i] or not texts[i].split() or same[tuple(texts[i].lower().split())] == i)}
    bad = {r["doc_id"] for r in decontamination.report(table(spark, DATA, "documents"), table(spark, DATA, "benchmark")).where("contaminated").collect()}
    assert kept[3][1] == kept[2][1] - bad
    assert {r["doc_id"] for r in corpus_pipeline.run(spark, DATA).collect()} == kept[3][1]


def test_sample_is_bounded_whatever_repeats(spark):
    docs = spark.range(3000).select(F.lit(1).cast("long").alias("doc_id"), F.concat(F.lit("text "), (F.col("id") % 700).cast("string")).alias("text"), F.lit("en").alias("lang"))
    labels = spark.createDataFrame([(1, 1, 1, "x"), (1, 1, 1, "x"), (2, 0, 0, "y")], LABELS)
    from rankspark.llm import common

    assert common.labelled_sample(docs, labels, "toxic", 100).count() == 100
    same = docs.withColumn("text", F.lit("one text"))
    assert common.labelled_sample(same, labels, "toxic", 100).count() == 1
    assert langid.train(docs, per_language=50).languages == ["en"]


def test_language_pieces_score_as_one_text():
    text, size = "Straße über ünïcode, naïve Σ words. " * 40, langid.PIECE
    model = langid.Model(["a", "b"], np.random.default_rng(1).normal(size=(1 << langid.BITS, 2)).astype(np.float32), np.zeros(2), 1.0, 0.0)
    whole, bag = model.logits(text), langid.bag(text)
    try:
        langid.PIECE = 7
        assert model.logits(text) == pytest.approx(whole, abs=1e-9) and all((x == y).all() for x, y in zip(langid.bag(text), bag, strict=True))
    finally:
        langid.PIECE = size


def test_hidden_insults_in_long_words():
    far = "x" * 100 + "1d1ot"
    short, long = toxicity.features((), "an !d!0t here"), toxicity.features((), f"an {far} here")
    assert short[10] == 1 and long[10] == 0
    assert toxicity.features((), "#" * 100 + "?" * 60 + "'1d1ot' x1x")[10] == 0 and toxicity.features((), "?" * 60 + "i.d.i.o.t" + "?" * 60)[10] == 1


def test_decontamination_by_both_paths(spark, tmp_path):
    rnd = random.Random(1)
    docs = [(i, " ".join(rnd.choice("abc") for _ in range(rnd.randint(0, 60)))) for i in range(120)] + [(None, "a b c"), (5, None), (6, "a " * 50)]
    items = [(i, " ".join(rnd.choice("abc") for _ in range(rnd.choice([0, 1, 3, 9, 10, 12, 14])))) for i in range(30)] + [(99, "a " * 12)]
    for kept in (items, [x for x in items if len(x[1].split()) >= 10]):
        d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(kept, "item_id long, text string")
        db = duckdb.connect()
        for name, df in (("documents", d), ("benchmark", b)):
            path = str(tmp_path / f"{name}{len(kept)}")
            df.write.parquet(path)
            db.execute(f"create view {name} as select * from '{path}/*.parquet'")
        told = db.execute(decontamination.SQL)
        names = [c[0] for c in told.description]
        want = sorted((tuple(r[names.index(c)] for c in sorted(names)) for r in told.fetchall()), key=str)
        for rows in (1_000_000, 1):
            got = decontamination.report(d, b, broadcast_rows=rows).drop("th")
            assert sorted((tuple(r[c] for c in sorted(names)) for r in got.collect()), key=str) == want


def test_near_duplicates_in_cells(spark, monkeypatch):
    docs = table(spark, DATA, "documents")
    whole = sorted(map(tuple, neardup.group(docs, 2).collect()))
    monkeypatch.setattr(neardup, "BLOCK", 2)
    monkeypatch.setattr(neardup, "HEAVY", 3)
    assert sorted(map(tuple, neardup.group(docs, 2).collect())) == whole
