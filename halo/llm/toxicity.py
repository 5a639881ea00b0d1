"""Toxicity of whole texts: subword-bag embeddings averaged into a linear softmax.

A word is the average of the embeddings of its hashed character n-grams (3 to 6, with word marks), a
passage of PASSAGE words is the average of its distinct words (short ones are padded with blanks, so that
neither a repeated nor a lone word passes for a whole passage), and a linear softmax turns that average into two
class probabilities. Embeddings and softmax are trained together in numpy by full-batch Adam: first on
whole texts, then on the passage of each toxic text that looks most toxic and on all passages of the others,
their worst one weighing most. A text is scored the same way: its score is that of its worst passage. So one insult is not thinned out by a long text, and unseen
spellings share the n-gram vectors of seen ones.

Learning uses a bounded sample of labelled rows: PER_CLASS texts of each class, those with the smallest
hash of their id. It runs in one task on an executor, which a lost executor repeats with the same result.
Everything else reads every row and whole texts. As the softmax is linear in an average, a trained model is
one number for each n-gram bucket and one bias; that is all the driver and the scoring tasks receive.

Defined results: null and empty texts score as a passage without evidence (the bias alone); rows that
repeat an id are scored each; without rows of both classes to learn from every score is 0; an empty
table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StringType, StructField, StructType

from halo.llm.common import fresh_name, hash_sample
from halo.llm.tokenise import _shared

PER_CLASS = (1600, 800)  # clean, toxic
BUCKETS = 1 << 18
DIM = 4
PASSAGE = 48
GRAMS = (3, 4, 5, 6)
WORD = re.compile(r"[^\W_]+")
CACHE_WORDS = 200_000
STRETCH = 1 << 18


def ngram_buckets(words: list[str], buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray]:
    """For all character n-grams of the marked words: position of the word, hash bucket."""
    if not words:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    chars = np.frombuffer("".join(f"<{w}>" for w in words).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    lengths = np.fromiter((len(w) + 2 for w in words), np.int64, len(words))
    word = np.repeat(np.arange(len(words)), lengths)
    end = np.repeat(np.cumsum(lengths), lengths)
    at = np.arange(len(chars))
    whose, where = [], []
    for n in GRAMS:
        k = np.flatnonzero(at + n <= end)
        h = np.full(len(k), n, np.uint64)
        for j in range(n):
            h = (h ^ chars[k + j]) * np.uint64(0x9E3779B97F4A7C15)
            h ^= h >> np.uint64(29)
        whose.append(word[k])
        where.append((h % np.uint64(buckets)).astype(np.int64))
    return np.concatenate(whose), np.concatenate(where)


def words_of(text: str | None) -> list[str]:
    return WORD.findall(text.lower()) if text else []


@dataclass
class SubwordModel:
    """weight: gain in log-odds of each n-gram bucket; bias: log-odds of a text without evidence."""

    weight: np.ndarray
    bias: float

    def word_scores(self, words: list[str]) -> np.ndarray:
        whose, where = ngram_buckets(words, len(self.weight))
        total = np.bincount(whose, self.weight[where], len(words))
        return total / np.maximum(np.bincount(whose, minlength=len(words)), 1)

    def score(self, texts: list[str | None], known: dict[str, float]) -> np.ndarray:
        split = [words_of(t) for t in texts]
        fresh = set().union(*split).difference(known) if split else set()
        extra: dict[str, float] = {}
        names = list(fresh)
        for k in range(0, len(names), 20_000):
            part = names[k : k + 20_000]
            extra.update(zip(part, self.word_scores(part).tolist()))
        room = CACHE_WORDS - len(known)
        known.update((w, extra[w]) for w in names[: max(0, room)])
        out = np.full(len(texts), self.bias)
        for k, ws in enumerate(split):
            if ws:
                values = [known[w] if w in known else extra[w] for w in ws]
                sums = [sum(dict(zip(ws[a : a + PASSAGE], values[a : a + PASSAGE])).values()) for a in range(0, len(ws), PASSAGE)]
                out[k] += max(sums) / PASSAGE
        return 1.0 / (1.0 + np.exp(-np.clip(out, -60, 60)))


def _all_ngrams(words: list[str], buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """ngram_buckets of many words, part by part, in 32-bit integers."""
    whose, where = [], []
    for k in range(0, len(words), 10_000):
        a, b = ngram_buckets(words[k : k + 10_000], buckets)
        whose.append((a + k).astype(np.int32))
        where.append(b.astype(np.int32))
    return np.concatenate(whose), np.concatenate(where)


class Segments:
    """Sums of values that share a key, by one sort ahead of many uses."""

    def __init__(self, keys: np.ndarray, picks: np.ndarray, size: int):
        order = np.argsort(keys, kind="stable")
        ordered = keys[order]
        self.starts = np.append(np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]])), len(ordered))
        self.keys, self.picks, self.size = ordered[self.starts[:-1]], picks[order].astype(np.int32), size
        # Whole segments of about STRETCH values together: what a sum holds at once does not grow with the sample.
        self.cuts = np.unique(np.append(np.searchsorted(self.starts, np.arange(0, len(ordered), STRETCH)), len(self.keys)))

    def sums(self, values: np.ndarray) -> np.ndarray:
        out = np.zeros(self.size)
        for a, b in zip(self.cuts[:-1], self.cuts[1:]):
            first = self.starts[a]
            out[self.keys[a:b]] = np.add.reduceat(values.take(self.picks[first : self.starts[b]]), self.starts[a:b] - first)
        return out


def adam(value: np.ndarray, gradient: np.ndarray, m: np.ndarray, v: np.ndarray, t: int, rate: float, floor: float) -> None:
    """Step t of Adam, in place."""
    m *= 0.9
    m += 0.1 * gradient
    v *= 0.98
    v += 0.02 * gradient * gradient
    value -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.98**t)) + floor)


def train(texts: list[str], labels: list[int], buckets: int = BUCKETS, dim: int = DIM, warm: int = 30, steps: int = 60, rate: float = 0.3, decay: float = 1e-6, easy: float = 0.2, floor: float = 1e-7, spread: float = 0.01, seed: int = 7) -> SubwordModel:
    """Fit embeddings, softmax and bias together."""
    y_all = np.asarray(labels)
    if len(set(labels)) < 2:
        return SubwordModel(np.zeros(buckets), -60.0)
    vocabulary: dict[str, int] = {}
    tokens, passage_of, doc_of, lengths = [], [], [], []
    for d, text in enumerate(texts):
        ws = words_of(text)
        for s in range(0, len(ws), PASSAGE):
            part = list(dict.fromkeys(ws[s : s + PASSAGE]))
            tokens.append(np.fromiter((vocabulary.setdefault(w, len(vocabulary)) for w in part), np.int64, len(part)))
            passage_of.append(np.full(len(part), len(lengths)))
            doc_of.append(d)
            lengths.append(len(part))
    if not tokens:
        return SubwordModel(np.zeros(buckets), -60.0)
    token, passage = np.concatenate(tokens), np.concatenate(passage_of)
    doc, size = np.array(doc_of), np.array(lengths, np.float64)
    whose, where = _all_ngrams(list(vocabulary), buckets)
    grams = np.maximum(np.bincount(whose, minlength=len(vocabulary)), 1).astype(np.float64)
    rng = np.random.default_rng(seed)
    words_of_grams, grams_of_words = Segments(whose, where, len(vocabulary)), Segments(where, whose, buckets)
    passages_of_tokens, tokens_of_passages = Segments(passage, token, len(size)), Segments(token, passage, len(vocabulary))
    del whose, where, token, passage, tokens, passage_of  # the segments hold what is needed of them
    embed = np.ascontiguousarray(rng.normal(0, spread, (buckets, dim)).T)  # component x bucket
    soft = rng.normal(0, 0.5, (dim, 2))
    bias = np.zeros(2)
    moments = [(np.zeros_like(p), np.zeros_like(p)) for p in (soft, bias)]
    embed_m, embed_v = np.zeros_like(embed), np.zeros_like(embed)

    def forward(k: int) -> np.ndarray:
        return passages_of_tokens.sums(words_of_grams.sums(embed[k]) / grams) / PASSAGE

    def backward(k: int, g: np.ndarray, t: int, now: float) -> None:
        g_embed = grams_of_words.sums(tokens_of_passages.sums(g) / grams) + decay * embed[k]
        adam(embed[k], g_embed, embed_m[k], embed_v[k], t, now, floor)

    pool = ThreadPoolExecutor(min(dim, 2))  # components do not meet but in the softmax
    y = y_all[doc]
    doc_words = np.bincount(doc, size, len(texts))
    for t in range(1, warm + steps + 1):
        mean = np.stack(list(pool.map(forward, range(dim))), 1)
        if t <= warm:  # every passage, so that a text weighs one
            weight = size / doc_words[doc]
        else:  # the most toxic passage of each text
            logit = mean @ (soft[:, 1] - soft[:, 0])
            order = np.lexsort((-logit, doc))
            first = order[np.concatenate([[True], doc[order][1:] != doc[order][:-1]])]
            weight = (y == 0) * easy
            weight[first] = 1.0
        for c in (0, 1):
            weight[y == c] *= 0.5 / max(weight[y == c].sum(), 1e-12)
        z = mean @ soft + bias
        z -= z.max(axis=1, keepdims=True)
        p = np.exp(z)
        p /= p.sum(axis=1, keepdims=True)
        p[np.arange(len(y)), y] -= 1
        p *= weight[:, None]
        g_soft, g_bias, g_mean = mean.T @ p, p.sum(axis=0), (p @ soft.T) / PASSAGE
        now = rate / (1 + 3 * t / (warm + steps))
        list(pool.map(lambda k: backward(k, np.ascontiguousarray(g_mean[:, k]), t, now), range(dim)))
        for (m, v), value, g in zip(moments, (soft, bias), (g_soft, g_bias)):
            adam(value, g, m, v, t, now, floor)
    pool.shutdown()
    return SubwordModel((soft[:, 1] - soft[:, 0]) @ embed, float(bias[1] - bias[0]))


def training_rows(docs: DataFrame, labels: DataFrame, allowed: Column, per_class: tuple[int, int] = PER_CLASS, text_col: str = "text", id_col: str = "doc_id", label_col: str = "toxic") -> DataFrame:
    """At most `per_class` labelled texts of each class (id, text, y), from rows whose id `allowed` admits."""
    rows = labels.select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("y")).where(F.col("id").isNotNull() & allowed)
    picked = [hash_sample(rows.where(F.col("y") == c), "id", per_class[c]) for c in (0, 1)]
    chosen = picked[0].unionByName(picked[1]).groupBy("id").agg(F.max("y").alias("y"))
    found = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(chosen), "id").where(F.length("text") > 0)
    return found.groupBy("id").agg(F.min("text").alias("text"), F.max("y").alias("y"))  # an id may repeat without bound


def training_sample(docs: DataFrame, labels: DataFrame, allowed: Column, **how) -> tuple[list[str], list[int]]:
    """The training rows as lists in order of id, for use outside Spark."""
    pairs = sorted((r.id, r.text, r.y) for r in training_rows(docs, labels, allowed, **how).collect())
    return [t for _, t, _ in pairs], [y for _, _, y in pairs]


def train_task(rows: DataFrame) -> SubwordModel:
    """`train` on a bounded table (id, text, y), in one task; the driver receives the weights only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _shared("toxic")  # caches of other operators leave this worker
        pairs = sorted(row for b in batches for row in zip(*(c.to_pylist() for c in b.columns)))
        model = train([t for _, t, _ in pairs], [y for _, _, y in pairs])
        yield pa.RecordBatch.from_arrays([pa.array([model.weight.astype("<f4").tobytes()], pa.binary()), pa.array([model.bias], pa.float64())], ["weight", "bias"])

    got = rows.select("id", "text", "y").repartition(1).mapInArrow(run, "weight binary, bias double").head()
    return train([], []) if got is None else SubwordModel(np.frombuffer(got.weight, "<f4").astype(np.float64), got.bias)


def score_documents(docs: DataFrame, model: SubwordModel, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",), score_col: str = "score") -> DataFrame:
    """The columns `keep` of `docs` and `score_col`, for every row. A text among `keep` travels to Python once."""
    weight, bias = model.weight.astype(np.float32), model.bias
    kept = list(keep)
    at = kept.index(text_col) if text_col in kept and docs.schema[text_col].dataType == StringType() else len(kept)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = SubwordModel(weight.astype(np.float64), bias)
        shared, mark = _shared("toxic"), hash((weight.tobytes(), bias))
        if shared.get("toxic_mark") != mark:
            shared.update(toxic_mark=mark, toxic_words={})
        for batch in batches:
            for s in range(0, batch.num_rows, 256):
                part = batch.slice(s, 256)
                score = own.score(part.column(at).to_pylist(), shared["toxic_words"])
                yield pa.RecordBatch.from_arrays([*part.columns[: len(kept)], pa.array(score, pa.float64())], [*kept, score_col])

    extra = [] if at < len(kept) else [F.col(text_col).cast("string").alias(fresh_name(kept, "text"))]
    frame = docs.select(*kept, *extra)
    schema = StructType([*frame.schema.fields[: len(kept)], StructField(score_col, DoubleType())])
    return frame.mapInArrow(run, schema)
