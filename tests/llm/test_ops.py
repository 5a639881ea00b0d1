"""The training-data operators against brute force, round trips and held-out accuracy."""

import collections
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

public_tokenizers = pytest.importorskip("public_tokenizers")

from halo.llm import exact_dedup, mixing, near_dedup, packing, quality, queries, rans, sharding, token_output, topk_search, toxicity, url_filter  # noqa: E402
from halo.llm.common import hash_sample  # noqa: E402

WORD = re.compile(r"[^\x20\x09-\x0D]+")
FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, digest string, size int"
ODD = [
    (1, "One two three four five six", "en", "a", 0, "x", 1), (2, "one TWO three four five six", "en", "a", 0, "x", 1), (3, None, None, None, None, None, None), (4, "", "en", "b", 0, None, 2),
    (5, "   \t\n", "en", "b", 0, None, 2), (6, "Ärger ÄRGER straße", "de", "a", 0, None, 2), (6, "Ärger ÄRGER straße", "de", "a", 0, None, 2), (None, "lonely null id", "en", "c", 0, None, 2),
    (7, "word " * 9000, "en", "a", 0, None, 2), (8, "x", "en", None, 0, None, 2), (9, "hello\u00a0 world <|endoftext|> it's  fine", "en", "a", 0, None, 2), (10, "z" * 30_000, "en", "a", 0, None, 1),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def test_sharding(spark, odd, none):
    names = [f"s{k}" for k in range(7)]
    table = sharding.lookup_table(names, 701)
    counts = collections.Counter(table)
    assert max(counts.values()) - min(counts.values()) <= 1
    fewer = sharding.lookup_table(names[:-1], 701)
    moved = sum(a != b for a, b in zip(table, fewer) if a != 6)
    assert moved < 0.2 * 701
    assert collections.Counter(sharding.lookup_table(names, 701, {"s0": 3}))[0] > 2 * 701 / 9
    got = sharding.place(odd, "doc_id", names, 701)
    assert got.count() == len(ODD) and sharding.place(none, "doc_id", names, 701).count() == 0
    assert sharding.balance(got).agg(F.sum("n_rows")).head()[0] == len(ODD)
    with pytest.raises(ValueError):
        sharding.lookup_table(names, 700)


def test_exact_dedup(spark, odd, none):
    got = exact_dedup.exact_dedup(odd)
    groups = collections.defaultdict(list)
    for r in ODD:
        groups[(r[1] or "").translate(FOLD)].append(r[0])
    rows = got.collect()
    assert len(rows) == len(ODD) and sum(r.kept for r in rows) == len(groups)
    for r in rows:
        mine = next(g for g in groups.values() if r.doc_id in g)
        assert r.group_size == len(mine) and r.keep_id == max((x for x in mine if x is not None), default=None)
    assert exact_dedup.exact_dedup(none).count() == 0
    kept = exact_dedup.drop_copies(odd, got)
    assert kept.columns == odd.columns and kept.count() == len(groups)


def test_exact_dedup_survives_digest_collisions_and_batches(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet").repartition(4)
    weak = exact_dedup.exact_dedup(docs, digest=lambda t: F.substring(F.sha2(t, 256), 1, 1), files_per_batch=1)
    strong = exact_dedup.exact_dedup(docs, files_per_batch=2)
    pick = ("doc_id", "keep_id", "group_size", "kept", "text_sha256")
    assert sorted(map(tuple, weak.select(*pick).collect())) == sorted(map(tuple, strong.select(*pick).collect()))


def test_rans_round_trip_checkpoints_and_damage():
    rng = np.random.default_rng(0)
    ids = np.minimum(rng.zipf(1.3, 60_000), 4999).astype(np.uint32)
    table = rans.Table.from_bytes(rans.Table(rans.scaled_table(np.bincount(ids, minlength=5000), 16), 16).to_bytes())
    for n in (0, 1, 63, 64, 1000, 60_000):
        block = rans.encode_block(ids[:n], table, every=8)
        assert np.array_equal(rans.decode_block(block, table), ids[:n])
    head = rans.read_header(block)
    parts = [rans.decode_block(block, table, s) for s in range(head["segments"])]
    assert head["segments"] > 2 and np.array_equal(np.concatenate(parts), ids)
    p = np.bincount(ids) / len(ids)
    entropy = -(p[p > 0] * np.log2(p[p > 0])).sum() / 8 * len(ids)
    plain = rans.encode_block(ids, table, lanes=32, every=10**6)
    assert len(plain) < 1.02 * entropy + 400
    with pytest.raises(ValueError):
        rans.decode_block(block[:-5] + bytes([block[-5] ^ 1]) + block[-4:], table)


def reference_ids(path, texts, end):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    return [np.array(t.encode(x or "", add_special_tokens=False).ids + [end], "<u4") for x in texts]


def test_token_output(spark, odd, none, tmp_path):
    vocab = queries.word_vocabulary()
    token_output.write_corpus(odd, str(tmp_path / "c"), vocab, files=3, block_ids=500)
    rows = token_output.read_corpus(spark, str(tmp_path / "c"), with_ids=True).orderBy("start").collect()
    want = sorted(ODD, key=lambda r: (r[0] is not None, r[0] or 0))
    ids = reference_ids(vocab.path, [r[1] for r in want], 2)
    assert [r.doc_id for r in rows] == [r[0] for r in want]
    assert [r.ids for r in rows] == [i.tolist() for i in ids] and [r.ids_crc32 for r in rows] == [zlib.crc32(i.tobytes()) for i in ids]
    assert [r.start for r in rows] == np.concatenate([[0], np.cumsum([len(i) for i in ids])[:-1]]).tolist()
    token_output.write_corpus(none, str(tmp_path / "e"), vocab, files=2)
    assert token_output.read_corpus(spark, str(tmp_path / "e")).count() == 0


def check_packing(rows, capacity):
    by = collections.defaultdict(list)
    for r in rows:
        by[r.sequence_id].append((r.offset, r.length))
    for parts in by.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= capacity
    return len(by)


def test_packing(spark, odd, none):
    vocab = queries.byte_vocabulary()
    from halo.llm.common import scratch_root, stash

    pieces = stash(packing.pieces_of(odd, vocab, 64, with_ids=True), scratch_root(spark) + "/p")
    placed = packing.pack(pieces, packing.Capacities(64)).cache()
    rows = placed.collect()
    ids = reference_ids(vocab.path, [r[1] for r in ODD], 0)
    assert sum(r.length for r in rows) == sum(map(len, ids))
    check_packing(rows, 64)
    seqs = {r.sequence_id: bytes(r.ids) for r in packing.sequences(placed).collect()}
    for r in rows:
        part = seqs[r.sequence_id][4 * r.offset : 4 * (r.offset + r.length)]
        assert zlib.crc32(part) == r.ids_crc32
    assert all(r.length == 64 for r in rows if r.piece > 0) and packing.cut(5, 5) == [(0, 5)] and packing.cut(12, 5) == [(0, 2), (2, 5), (7, 5)]
    assert packing.pack(stash(packing.pieces_of(none, vocab, 64), scratch_root(spark) + "/e"), packing.Capacities(64)).count() == 0


@pytest.mark.parametrize("rule", ["norm", "dot"])
@pytest.mark.parametrize("capacities", [packing.Capacities(100), packing.Capacities(100, 3), packing.Capacities(100, 50, 6000)])
def test_packing_plan_respects_every_capacity(rule, capacities):
    rng = np.random.default_rng(3)
    lengths = rng.integers(1, 77, 500)
    hist = collections.Counter(lengths.tolist())
    seen, bins = collections.Counter(), collections.defaultdict(list)
    for length, a, b, seq, off in packing.plan(dict(hist), capacities, rule):
        seen[length] += b - a
        for k in range(b - a):
            bins[seq + k].append((off, length))
    assert seen == hist
    cap = capacities.vector()
    for parts in bins.values():
        assert sum(n for _, n in parts) <= cap[0] and len(parts) <= cap[1] and sum(n * n for _, n in parts) <= cap[2]
        ends = np.cumsum([n for _, n in sorted(parts)])
        assert [o for o, _ in sorted(parts)] == [0, *ends[:-1]]
    if capacities.documents is None:
        assert len(bins) <= 1.03 * -(-lengths.sum() // 100)


def test_topk_search(spark):
    rng = np.random.default_rng(5)
    rows = [(i, rng.normal(size=20).round(1).tolist()) for i in range(300)] + [(300, None), (301, [1.0, None] + [0.0] * 18), (302, [float("nan")] * 20), (303, [1.0] * 7), (304, [0.0] * 20), (305, [2.0] * 7)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    got = collections.defaultdict(list)
    for r in topk_search.top_k(df, F.col("vec_id") % 10 == 0, 4, query_block=16).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.vec_id, r.score))
    good = [(i, np.floor(256 * np.array(v, float))) for i, v in rows if v is not None and None not in v and np.isfinite(v).all()]
    for q, v in good:
        if q % 10 == 0:
            cand = sorted((-int(v @ w), i) for i, w in good if i != q and len(w) == len(v))[:4]
            assert got[q] == [(i, -s) for s, i in cand]
    huge = spark.createDataFrame([(0, [1e9, 1e9]), (1, [1e9, -1e9]), (2, [2e9, 1.0])], "vec_id bigint, embedding array<double>")
    assert [r.vec_id for r in topk_search.top_k(huge, F.col("vec_id") == 0, 2, scale=1).orderBy("rank").collect()] == [2, 1]
    assert topk_search.top_k(df.limit(0), F.lit(True), 3).count() == 0


@pytest.mark.parametrize("block", [2, 4096])
def test_topk_search_with_every_vector_of_a_repeated_query_id(spark, block):
    rng = np.random.default_rng(6)
    rows = [(i % 40, rng.normal(size=6).round(1).tolist()) for i in range(120)] + [(0, [3.0] * 6)] * 2
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    got = collections.defaultdict(list)
    for r in topk_search.top_k(df, F.col("vec_id") % 10 == 0, 4, query_block=block).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.vec_id, r.score))
    whole = [(i, tuple(np.floor(256 * np.array(v)))) for i, v in rows]
    for q in (0, 10, 20, 30):
        asked = {v for i, v in whole if i == q}
        want = sorted((-int(np.dot(v, w)), i) for v in asked for i, w in whole if i != q)[:4]
        assert len(asked) > 2 and got[q] == [(i, -s) for s, i in want]


def brute_components(texts, ids, w, percent):
    sets = []
    for t in texts:
        words = WORD.findall((t or "").translate(FOLD))
        sets.append({tuple(words[k : k + w]) for k in range(len(words) - w + 1)} if len(words) >= w else ({tuple(words)} if words else set()))
    label = list(ids)
    pairs = [(i, j) for i in range(len(sets)) for j in range(i) if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j])]
    changed = True
    while changed:
        changed = False
        for i, j in pairs:
            low = min(label[i], label[j])
            if label[i] != low or label[j] != low:
                label[i] = label[j] = low
                changed = True
    return dict(zip(ids, label)), dict(zip(ids, map(len, sets)))


def family(seed=0):
    """One original, many edited copies around the threshold, exact copies and bystanders."""
    rng = np.random.default_rng(seed)
    base = [f"w{rng.integers(400)}" for _ in range(120)]
    texts = [" ".join(base)] * 5
    for k in range(150):
        own = list(base)
        for at in rng.integers(0, 120, rng.integers(0, 14)):
            own[at] = f"e{rng.integers(30)}"
        texts.append(" ".join(own))
    texts += [" ".join(f"w{rng.integers(400)}" for _ in range(rng.integers(1, 60))) for _ in range(60)]
    return texts + ["a b", "A B", "a", "", None]


@pytest.mark.parametrize("words,rounds,block", [(2, 2, 2048), (5, 1, 16), (2, 0, 16)])
def test_near_dedup(spark, monkeypatch, words, rounds, block):
    monkeypatch.setattr(near_dedup, "BLOCK", block)
    texts = family()
    ids = list(np.random.default_rng(1).permutation(1000)[: len(texts)].tolist())
    df = spark.createDataFrame(list(zip(ids, texts)), "doc_id bigint, text string").repartition(5)
    rows = near_dedup.near_groups(df, near_dedup.NearConfig(words=words, star_rounds=rounds)).collect()
    want, n = brute_components(texts, ids, words, 80)
    assert {r.doc_id: r.component_id for r in rows} == want and {r.doc_id: r.n_shingles for r in rows} == n
    assert all(r.kept == (r.doc_id == r.component_id) for r in rows)


def test_near_dedup_odd_rows(odd, none):
    rows = near_dedup.near_groups(odd).collect()
    assert len(rows) == len(ODD) and near_dedup.near_groups(none).count() == 0
    assert next(r for r in rows if r.doc_id is None).component_id is None
    assert next(r for r in rows if r.doc_id == 2).component_id == 1


def test_index_keys_meet_the_guarantee():
    c = near_dedup.NearConfig()
    rng = np.random.default_rng(2)
    for _ in range(200):
        a = rng.integers(0, 2**16, c.coords).astype(np.uint16)
        b = a.copy()
        b[rng.permutation(c.coords)[: c.guaranteed_distance]] += 1
        k = near_dedup.chunk_keys(np.stack([a, b]), c)
        assert set(k[0]) & set(k[1])


def test_components(spark):
    chain = [(k, k + 1) for k in range(40)] + [(100 + k, 100) for k in range(1, 9)] + [(7, 7)]
    got = {r.v: r.label for r in near_dedup.components(spark.createDataFrame(chain, "a bigint, b bigint"), f"{spark.conf.get('spark.checkpoint.dir')}/cc").collect()}
    assert got == {**{k: 0 for k in range(1, 41)}, **{100 + k: 100 for k in range(1, 9)}}


def test_mixing(spark, odd, none, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    made = mixing.mix(docs, mixing.MixConfig(block_words=32))
    rows = made.taken().collect()
    again = mixing.mix(docs.repartition(7), mixing.MixConfig(block_words=32)).taken().collect()
    assert sorted(map(tuple, rows)) == sorted(map(tuple, again)) and len(rows) == docs.count()
    src = {r.doc_id: r.source for r in docs.select("doc_id", "source").collect()}
    taken, goal = collections.Counter(), {}
    for r in rows:
        assert r.taken <= 3 * r.size
        taken[src[r.doc_id]] += r.taken
        goal[src[r.doc_id]] = r.target
    assert all(abs(taken[s] - g) <= 40 + 0.02 * g for s, g in goal.items())
    assert made.output().agg(F.sum("words")).head()[0] == sum(taken.values())
    mixed = mixing.mixed_texts(docs, made)
    words = {r.doc_id: r.n for r in mixed.groupBy("doc_id").agg(F.sum(mixing.word_count(F.col("text"))).alias("n")).collect()}
    assert mixed.columns == docs.columns and words == {r.doc_id: r.taken for r in rows if r.taken}
    assert mixing.mix(odd).taken().count() == len(ODD) and mixing.mix(none).taken().count() == 0
    assert mixing.targets([10, 100, 100], [5, 2, 1], 3) == [30.0, 120.0, 60.0]
    for n in (1, 2, 3, 17, 1000):
        p = mixing.permute(np.arange(n), n, np.full(n, 99, np.uint64))
        assert sorted(p.tolist()) == list(range(n))


def test_toxicity_on_held_out_rows():
    rng = np.random.default_rng(4)
    clean = [f"{a}{b}" for a in ("ar", "bel", "cor", "dun", "fil", "gos") for b in ("an", "eth", "ing", "ol", "um")]
    bad = ["stupidity", "moronic", "scumbag"]

    def text(y, words):
        ws = rng.choice(clean, rng.integers(30, 200)).tolist()
        for _ in range(3 * y):
            ws[rng.integers(len(ws))] = words[rng.integers(len(words))]
        return " ".join(ws)

    y = [k % 2 for k in range(300)]
    model = toxicity.train([text(v, bad) for v in y], y, buckets=1 << 14)
    unseen = ["stupidly", "moronics", "scumbags"]  # other spellings
    s = model.score([text(1, unseen) for _ in range(50)] + [text(0, bad) for _ in range(50)] + ["", None], {})
    assert (s[:50] >= 0.3).mean() > 0.9 and (s[50:100] < 0.3).mean() > 0.9 and np.isfinite(s).all()
    assert toxicity.train(["a"], [1]).score(["x", None], {}).max() < 1e-9


def test_toxicity_scores_odd_rows(odd, none):
    model = toxicity.SubwordModel(np.zeros(64), -1.0)
    rows = toxicity.score_documents(odd, model).collect()
    assert len(rows) == len(ODD) and all(0 <= r.score <= 1 for r in rows) and toxicity.score_documents(none, model).count() == 0


URLS = ["http://A.Example.org/es/x?q=1", "https://example.org/en/12", "http://notexample.org/es/", "http://x.com/fr/a#b", "http://x.com/de/", "ftp://com/de/1", "http://a.org", "no scheme", None, "", "http://net?x://y", "http://u.net/a/b/c?x=1&y=2"]


def python_judge(u):
    if u is None or "://" not in u:
        return "", "", None
    rest = u.split("://", 1)[1]
    host = re.match(r"[^/?#]*", rest).group()
    path = re.match(r"[^?#]*", rest[len(host) :]).group()
    host = host.translate(FOLD)
    best = None
    for r, _ in queries.URL_RULES:
        h, _, p = r.partition("/")
        if (host == h or host.endswith("." + h)) and path.startswith("/" + p) and (best is None or len(r) > len(best)):
            best = r
    return host, path, best


def test_hash_sample_equals_a_full_sort(spark, none):
    rows = spark.range(30_000).selectExpr("if(id % 3 = 0, 7, id % 9000) AS k", "id AS v")
    for most in (1, 500, 20_000):
        want = rows.groupBy("k").agg(F.min("v").alias("v")).orderBy(F.xxhash64("k"), "k").limit(most)
        assert hash_sample(rows, "k", most).collect() == want.collect()
    assert hash_sample(none.select("doc_id"), "doc_id", 5).count() == 0


def test_learning_takes_one_text_of_a_repeated_id(spark):
    docs = spark.createDataFrame([(k % 4, f"text {k}") for k in range(400)], "doc_id bigint, text string")
    labels = spark.createDataFrame([(k % 4, k % 2) for k in range(400)], "doc_id bigint, toxic int")
    texts, marks = toxicity.training_sample(docs, labels, F.lit(True))
    assert (texts, marks) == (["text 0", "text 1", "text 10", "text 103"], [0, 1, 0, 1])


def test_url_filter(spark):
    pages = spark.createDataFrame([(k, u, "x") for k, u in enumerate(URLS)], "page_id bigint, url string, rule string")
    train = [f"http://{h}.net/{k}" for k in range(40) for h in ("good", "fine", "cheap-pills", "casino")]
    model = url_filter.UrlModel.train(train, [int("pills" in u or "casino" in u) for u in train])
    fresh = [f"http://{h}.net/9{k}" for k in range(9) for h in ("good", "cheap-pills")]
    assert ((model.score(fresh) > 0.5) == ["pills" in u for u in fresh]).all()
    for r in url_filter.judge(pages, queries.URL_RULES, model).collect():
        host, path, rule = python_judge(URLS[r.page_id])
        assert (r.host, r.path, r.rule) == (host, path, rule)
        assert r.verdict == (dict(queries.URL_RULES)[rule] if rule else ("block" if r.score >= 0.5 else "allow"))
    assert url_filter.judge(pages.limit(0), queries.URL_RULES, url_filter.UrlModel.train([], [])).count() == 0


def test_quality(spark, odd, none, tiny):
    rng = np.random.default_rng(0)
    truth = rng.random(4000) < 0.8
    right = np.array([0.9, 0.85, 0.7, 0.95])
    cast = np.where(rng.random((4000, 4)) < right, truth[:, None], ~truth[:, None]).astype(int)
    cast[rng.random((4000, 4)) < 0.2] = 2
    patterns, counts = np.unique(cast, axis=0, return_counts=True)
    model = quality.fit_labels(patterns, counts.astype(float))
    assert abs(model.prior - 0.8) < 0.05 and np.abs(model.accuracy() - right).max() < 0.05
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = quality.classify(docs).join(spark.read.parquet("/root/testdata/sf0.01/labels.parquet"), "doc_id").toPandas()
    assert got[got.quality == 1].kept.mean() > 0.95 and got[got.quality == 0].kept.mean() < 0.3
    assert quality.classify(odd).count() == len(ODD) and quality.classify(none).count() == 0


def test_pipeline_keeps_columns_and_decisions(spark, tiny):
    import corpus_pipeline

    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    names = docs.columns
    sizes = [docs.count()]
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        from halo.llm.common import scratch_root, stash

        docs = stash(stage(spark, docs, tiny), scratch_root(spark) + "/stage")
        sizes.append(docs.count())
        if k < 4:
            assert docs.columns == names
        if k in (1, 2):
            assert docs.select("doc_id").distinct().count() == docs.count()
    assert sizes[1] <= sizes[0] and sizes[2] <= sizes[1] and sizes[3] <= sizes[2]
    check_packing(docs.collect(), 2048)


@pytest.mark.parametrize("hot", [1000, 3])
def test_url_suffixes_are_counted_over_the_whole_table(spark, tmp_path, monkeypatch, hot):
    """A blocked host outside the learning sample still has its counts, and every count equals a loop over all URLs."""
    monkeypatch.setattr(url_filter, "HOT", hot)  # 3: most keys meet by a shuffle
    rows = [(k, f"http://{'casino' if k % 2 else 'acsino'}{k % 100 // 2:02}.net/{k:04}") for k in range(1200)]
    rows += [(2000 + k, u) for k, u in enumerate(URLS)] + [(3000 + k, "http://a.b.casino.com/q") for k in range(50)]
    pages = spark.createDataFrame(rows, "page_id bigint, url string")
    label = url_filter.seed_label(F.col("url"))
    counts = url_filter.corpus_counts(pages, label, str(tmp_path))
    seen, blocked = collections.Counter(), collections.Counter()
    for u in {u for _, u in rows if u is not None}:
        host, _, _ = python_judge(u)
        for s in url_filter.suffixes(host):
            seen[s] += 1
            blocked[s] += any(w in host for w in url_filter.SEED_TERMS)
    got = counts.rows.collect()
    assert len({r.suffix_key for r in got}) == len(got)
    for r in got:
        for k, s in enumerate(url_filter.suffixes(r.suffix_key), 1):
            assert (r[f"b0_{k}"] + r[f"b1_{k}"], r[f"s0_{k}"] + r[f"s1_{k}"]) == (blocked[s], seen[s]), s
    assert counts.total[1] + counts.total[3] == len({u for _, u in rows if u is not None})
    sample = url_filter.sample_rows(pages, label, most=80)
    model = url_filter.UrlModel.train_on_corpus(sample, counts)
    learnt = {python_judge(r.u)[0] for r in sample.collect()}
    out = url_filter.judge(pages, [], model, counts=counts).collect()
    assert collections.Counter(r.page_id for r in out) == collections.Counter(k for k, _ in rows)
    unseen = [r for r in out if r.page_id < 1200 and r.host not in learnt]
    assert len(unseen) > 100 and all((r.verdict == "block") == ("casino" in r.host) for r in unseen)
    stats = url_filter.SuffixStats(counts.prior(), dict(blocked), dict(seen))
    key = [url_filter.suffixes(r.suffix_key) for r in got]
    levels = np.array([[r[c] for c in url_filter.LEVELS] for r in got])
    assert np.allclose(counts.columns([r.suffix_key for r in got], levels), stats.columns(key))
    none = pages.limit(0)
    empty = url_filter.corpus_counts(none, label, str(tmp_path / "none"))
    assert url_filter.judge(none, [], url_filter.UrlModel.train_on_corpus(url_filter.sample_rows(none, label), empty), counts=empty).count() == 0
