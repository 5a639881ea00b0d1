"""Edges of the training-data operators: clashing column names, odd texts, huge numbers, the pipeline by brute force."""

import collections
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

public_tokenizers = pytest.importorskip("public_tokenizers")

from halo.llm import mixing, queries, token_output, topk_search, toxicity, url_filter  # noqa: E402
from halo.llm.common import fresh_name, scratch_root, stash  # noqa: E402
from halo.llm.tokenise import PieceEncoder  # noqa: E402
from tests.llm.test_ops import FOLD, WORD, brute_components, check_packing, reference_ids  # noqa: E402

# Texts that cut words, fold case, compose marks or name special tokens.
PARTS = [
    "a", "Z", "the", "ING", "'s", "'LL", "’", "1", "4567", ".", ",", "!", "?", "|", ")", "(", "-", "_", "  ", " ", "\t", "\n", "\r", "İ", "ı", "ß", "ẞ", "ǅ",
    "ŉ", "é", "́", "Å", "ɐ", "ΑΣ", "中", "ا", "가", "\U0001f600", "‍", " ", "\u0085", "\x0b", "\x1c", "ﬁ", "Ĳ",
    "ſ", "<|endoftext|>", "</w>", "Ġ", "\x00", "­", "ͅ", "@", "#", "{", "\\", "/", "~", ":", ";", '"',
]


def odd_text(rng: random.Random) -> str:
    out = []
    for _ in range(rng.randrange(1, 12)):
        low, high = rng.choice([(32, 127), (0xA0, 0x250), (0x250, 0x2100), (0x300, 0x370), (0x1E00, 0x2000)])
        out.append(rng.choice(PARTS) if rng.random() < 0.7 else chr(rng.randrange(low, high)))
    return "".join(out)


@pytest.mark.parametrize("vocab", [queries.word_vocabulary(), queries.byte_vocabulary()], ids=["words", "bytes"])
def test_piece_cache_equals_the_library(vocab):
    rng = random.Random(9)
    texts = ["İ.", "İ", "xİ, y", *(odd_text(rng) for _ in range(100_000))]
    encoder = PieceEncoder(vocab.path, vocab.keeps_space)
    for k in range(0, len(texts), 5000):
        part = texts[k : k + 5000]
        want = encoder.tokenizer.encode_batch(part, add_special_tokens=False)
        got = encoder.encode(part, vocab.end_id)
        for text, g, w in zip(part, got, want):
            assert np.frombuffer(g, "<u4").tolist() == [*w.ids, vocab.end_id], ascii(text)


@pytest.mark.parametrize("block", [2, 4096])
def test_search_with_huge_components(spark, block):
    big = [(0, [1e20, 1.0]), (1, [2e18, -1.0]), (2, [-1e300, 1e300]), (3, [1e306, 0.0]), (4, [1.0, 1.0]), (5, [3e9, -7e9]), (6, [1.5, 2.5])]
    df = spark.createDataFrame(big, "vec_id bigint, embedding array<double>")
    got = collections.defaultdict(list)
    for r in topk_search.top_k(df, F.lit(True), 3, query_block=block).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.vec_id, r.score))
    whole = [(i, [topk_search.whole(x, 256) for x in v]) for i, v in big]
    for q, v in whole:
        near = sorted((-min(2**63 - 1, max(-(2**63), sum(a * b for a, b in zip(v, w)))), i) for i, w in whole if i != q)[:3]
        assert got[q] == [(i, -s) for s, i in near]


def test_search_reads_less_where_the_mass_is_uneven():
    rng = np.random.default_rng(1)
    matrix = np.floor(rng.normal(size=(64, 4000)) * np.repeat([200, 20, 2, 1], 16)[:, None])
    queries_ = np.floor(rng.normal(size=(70, 64)) * np.repeat([200, 20, 2, 1], 16))
    floor, visited = np.full(70, -np.inf), 0
    for q, where, score, visited in topk_search.search_block(np.arange(4000), matrix, np.arange(70) + 10_000, queries_, 5, floor):
        full = queries_[q] @ matrix
        want = np.lexsort((np.arange(4000), -full))[:5]
        assert where.tolist() == want.tolist() and score.tolist() == full[want].tolist()
    assert visited < 0.6 * 70 * matrix.size


def test_one_task_learns_what_the_driver_would(spark):
    rows = [(k, f"plain words number {k % 7} here", 0) for k in range(40)] + [(100 + k, f"you scumbag number {k % 7}", 1) for k in range(40)]
    there = toxicity.train_task(spark.createDataFrame(rows, "id bigint, text string, y int"))
    here = toxicity.train([t for _, t, _ in rows], [y for _, _, y in rows])
    assert np.array_equal(there.weight, here.weight.astype(np.float32)) and there.bias == here.bias
    none = toxicity.train_task(spark.createDataFrame([], "id bigint, text string, y int"))
    assert none.score(["x"], {}).max() < 1e-9


def test_url_labels_match_whole_words(spark):
    hosts = {"casino-win.example.com": 1, "m.free-bets.example.com": 1, "casino07.net": 1, "uploads.example.com": 0, "roads.org": 0, "alphabets.org": 0, "soundtrack.net": 0, "myadsite.com": 0}
    df = spark.createDataFrame([(f"http://{h}/casino/ads", y) for h, y in hosts.items()], "url string, y int")
    assert df.where(url_filter.seed_label(F.col("url")) != F.col("y")).count() == 0


CLASH = ["_text", "score", "_score", "_id", "_content", "_key", "_spans", "_size", "_sha", "_sha_", "_text_sha", "locator", "digest", "id", "component_id", "kept", "uses", "block", "sidx", "content"]


def test_fresh_names():
    assert fresh_name(["a", "_ID", "__id"], "id") == "___id" and fresh_name([], "id") == "_id"


def test_stages_pass_clashing_columns_nulls_and_repeats(spark, tiny):
    import corpus_pipeline

    rows = [(1, "One two three four five six"), (2, "one TWO three four five six"), (3, None), (4, ""), (4, ""), (None, "a null id of its own"), (5, "  \t\n"), (6, "word " * 9000), (7, "Ärger straße")]
    full = [(*r, "en", "a" if k % 2 else None, 0, *(f"{c}{k}" for c in CLASH)) for k, r in enumerate(rows)]
    schema = "doc_id bigint, text string, lang string, source string, n_chars bigint, " + ", ".join(f"`{c}` string" for c in CLASH)
    for data in (full, []):
        docs = spark.createDataFrame(data, schema)
        names, left = docs.columns, []
        for name, stage in corpus_pipeline.STAGES:
            docs = stash(stage(spark, docs, tiny), scratch_root(spark) + "/stage")
            left.append(docs.count())
            if name != "packing":
                assert docs.columns == names
                for r in docs.collect():  # a row keeps its own extra columns
                    assert r["_content"][-1] == r["_id"][-1]
            if name == "mixing":
                assert {r.doc_id for r in docs.collect()} <= {1, 2, 6, 7, None}
        # Equal texts: 1 and 2, then 3 and both rows of 4.
        assert left[:3] == ([9, 6, 6] if data else [0, 0, 0])


def test_pipeline_by_brute_force(spark, tiny):
    """Every stage's rows against plain Python on its own input."""
    import corpus_pipeline

    def step(k, docs):
        return stash(corpus_pipeline.STAGES[k][1](spark, docs, tiny), scratch_root(spark) + "/stage")

    def rows_of(df):
        return [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]

    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    given = rows_of(docs)
    model = queries.toxic_model(docs, spark.read.parquet(f"{tiny}/labels.parquet"))
    score = model.score([t for _, t in given], {})
    clean = step(0, docs)
    assert sorted(rows_of(clean)) == sorted(r for r, s in zip(given, score) if s < queries.TOXIC_AT)

    best: dict[str, int] = {}
    for i, t in rows_of(clean):
        key = (t or "").translate(FOLD)
        best[key] = max(best.get(key, i), i)
    single = step(1, clean)
    assert sorted(i for i, _ in rows_of(single)) == sorted(best.values())

    ids, texts = zip(*rows_of(single))
    label, _ = brute_components(texts, ids, 5, 80)
    lone = step(2, single)
    assert sorted(i for i, _ in rows_of(lone)) == sorted(i for i in ids if label[i] == i)

    taken = {r.doc_id: r.taken for r in mixing.mix(lone).taken().collect()}
    mixed = step(3, lone)
    before, words, seen = dict(rows_of(lone)), collections.Counter(), collections.defaultdict(collections.Counter)
    for i, t in rows_of(mixed):
        words[i] += len(WORD.findall(t))
        seen[i].update(WORD.findall(t))
    assert {i: n for i, n in taken.items() if n} == dict(words)
    for i, c in seen.items():
        own = collections.Counter(WORD.findall(before[i]))
        assert all(n <= 3 * own[w] for w, n in c.items())

    packed = step(4, mixed).collect()
    check_packing(packed, 2048)
    tokens = reference_ids(queries.byte_vocabulary().path, [t for _, t in rows_of(mixed)], 0)
    want = collections.Counter()
    for (i, _), t in zip(rows_of(mixed), tokens):
        first = len(t) % 2048 or 2048
        cuts = [(0, min(first, len(t))), *((s, s + 2048) for s in range(first, len(t), 2048))]
        want.update((i, k, a, b - a, zlib.crc32(t[a:b].tobytes())) for k, (a, b) in enumerate(cuts))
    assert collections.Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in packed) == want


def test_token_output_deals_one_id_over_files(spark, tmp_path):
    rows = [(7, f"word {k} of a hot id") for k in range(3000)] + [(None, f"no id {k}") for k in range(500)] + [(k, f"own text {k}") for k in range(0, 400, 3)]
    random.Random(3).shuffle(rows)
    vocab, path = queries.word_vocabulary(), str(tmp_path / "c")
    token_output.write_corpus(spark.createDataFrame(rows, "doc_id bigint, text string").repartition(5), path, vocab, files=8, block_ids=2000)
    got = token_output.read_corpus(spark, path).orderBy("start").collect()
    crc = [zlib.crc32(i.tobytes()) for i in reference_ids(vocab.path, [t for _, t in rows], 2)]
    assert collections.Counter((r.doc_id, r.ids_crc32) for r in got) == collections.Counter((i, c) for (i, _), c in zip(rows, crc))
    assert [r.start for r in got] == np.concatenate([[0], np.cumsum([r.n_tokens for r in got])[:-1]]).tolist()
    order = [(r.doc_id is not None, r.doc_id or 0) for r in got]
    assert order == sorted(order)
    blocks = token_output.read_blocks(spark, path).collect()
    hot = {b.file_no: int((np.frombuffer(b.doc_ids, "<i8") == 7).sum()) for b in blocks}
    assert sum(n > 0 for n in hot.values()) >= 4


def test_hot_keys_are_told_apart_without_a_join(spark, monkeypatch):
    """A join by key would make every row of a hot key again; both a hot and a cold key meet their one row of the table."""
    from halo.llm import near_dedup

    monkeypatch.setattr(near_dedup, "HOT", 2)
    rows = spark.range(900).select("id", F.when(F.col("id") < 800, 7).otherwise(F.col("id")).cast("bigint").alias("key"))
    table = rows.groupBy("key").agg(F.count(F.lit(1)).alias("m")).where("key < 850")
    got = near_dedup.meet(rows, table, "key", "m")
    assert "LeftOuter" not in got._jdf.queryExecution().optimizedPlan().toString()
    assert sorted((r.id, r.m) for r in got.collect()) == [(k, 800 if k < 800 else 1) for k in range(850)]


def test_joins_by_key_have_one_form_and_give_each_row_once(spark):
    """Without a hot key the join had another form, so its rows could not be compared with those of a table that has one."""
    from halo.llm import near_dedup

    def met(size):
        rows = spark.range(6000).select("id", F.when(F.col("id") < size, -1).otherwise(F.col("id") % 2000).cast("bigint").alias("key"))
        table = rows.groupBy("key").agg(F.count(F.lit(1)).alias("m"))
        got = near_dedup.meet(rows, table, "key", "m")
        assert "_salt" in got._jdf.queryExecution().optimizedPlan().toString()
        assert got.count() == got.select("id").distinct().count() == 6000
        return {r.m for r in got.where("key = -1").select("m").distinct().collect()}

    assert [met(size) for size in (0, 1, 2000, 4000)] == [set(), {1}, {2000}, {4000}]
    rows = spark.range(10).select("id", F.col("id").alias("key"))
    assert near_dedup.meet(rows, rows.groupBy("key").agg(F.count(F.lit(1)).alias("m")).where("m > 1"), "key", "m").isEmpty()


def test_words_met_before_are_not_cut_again():
    """Cutting at punctuation costs most of a warm encoder's time: once for each distinct word is enough."""
    vocab, cuts = queries.word_vocabulary(), []

    class Counting:
        def findall(self, text, own=PieceEncoder(vocab.path, False).pattern):
            cuts.append(text)
            return own.findall(text)

    encoder = PieceEncoder(vocab.path, vocab.keeps_space)
    encoder.pattern = Counting()
    first = encoder.encode(["Well, a (b) well, 'c!", None], vocab.end_id)
    before = len(cuts)
    assert encoder.encode(["Well, a (b) well, 'c!", None], vocab.end_id) == first and len(cuts) == before == 4


def test_each_distinct_word_is_looked_up_once_a_call():
    """Words that come again cost an index; plain words and marks after letters cost no search of the library's own."""
    vocab = queries.word_vocabulary()
    encoder = PieceEncoder(vocab.path, vocab.keeps_space)
    texts = ["", None, " The  cat,\tthe CAT%%% \r\nthe\ncat,", "the" * 3 + "%%%", "x\u2003y", " "] * 40 + ["\u00c9t\u00e9 \u0130 \u00e9t\u00e9%%% (632) a1b2"]
    want = [[*e.ids, vocab.end_id] for e in encoder.tokenizer.encode_batch([t or "" for t in texts], add_special_tokens=False)]

    class Counting(dict):
        asked = 0

        def get(self, name, default=None):
            Counting.asked += 1
            return dict.get(self, name, default)

    encoder.known = Counting()
    for _ in range(2):
        Counting.asked = 0
        assert [np.frombuffer(x, "<u4").tolist() for x in encoder.encode(texts, vocab.end_id)] == want
        assert Counting.asked <= 20
    assert {"the", "%%%"} <= set(encoder.known)
    assert encoder.encode([], vocab.end_id) == []
