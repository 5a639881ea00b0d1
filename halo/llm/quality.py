"""Document quality from weak labels: expectation-maximisation over heuristic labellers, then a hashed linear scorer.

Each labeller votes good, bad or abstains on every whole text. Texts with the same votes are alike, so
the votes of all texts are counted by pattern (at most 3^8, whatever the corpus) and the model of
labellers (a prior, and for each labeller the chance of each vote under either class) is estimated by
expectation-maximisation on those exact counts. Its posteriors label a bounded sample (SAMPLE texts with the
smallest hash of their id), on which a logistic scorer over hashed words and hashed coarse statistics
learns; the scorer judges every text.

Defined results: null and empty texts get the votes of an empty text and are scored like others; rows
that repeat an id are scored each; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from halo.llm.common import hash_sample, scratch_root, stash
from halo.llm.tokenise import _shared

SAMPLE = 4000
HASHED = 1 << 16
CACHE_WORDS = 200_000
# Frequent function words of the corpus languages.
FUNCTION_WORDS = frozenset("a al and are as at be but by con das de del den der des die el en es et for from has ich in is ist it la las le les los mit not of on que se sich the to un une und une von was with y zu".split())
LABELLERS = ("length", "variety", "capitals", "symbols", "lines", "word_size", "function_words", "top_word")


def statistics(text: str | None) -> dict[str, float]:
    t = text or ""
    words = t.split()
    n = max(len(words), 1)
    lines = [x for x in t.split("\n") if x.strip()]
    sample = max(len(t), 1)
    letters = sum(map(len, words)) or 1
    low = [w.lower().strip(".,;:!?") for w in words]
    counts: dict[str, int] = {}
    for w in low:
        counts[w] = counts.get(w, 0) + 1
    upper = sum(1 for w in words if w.isupper() and len(w) > 1)
    marks = sum(t.count(c) for c in "|!#*{}<>=_~^\\$%@")
    return {
        "words": len(words), "variety": len(counts) / n**0.8, "capitals": upper / n, "symbols": marks / n,
        "lines": 1 - len(set(lines)) / max(len(lines), 1), "word_size": letters / n, "function_words": sum(counts.get(w, 0) for w in FUNCTION_WORDS) / n,
        "top_word": max(counts.values(), default=0) / n, "size": sample,
    }


def votes(s: dict[str, float]) -> list[int]:
    """0 bad, 1 good, 2 abstain; one for each of LABELLERS."""

    def between(x, bad_low=None, good=(None, None), bad_high=None):
        if bad_low is not None and x < bad_low or bad_high is not None and x > bad_high:
            return 0
        lo, hi = good
        return 1 if (lo is None or x >= lo) and (hi is None or x <= hi) else 2

    return [
        between(s["words"], 8, (30, None)),
        between(s["variety"], 0.45, (0.9, None)),
        between(s["capitals"], None, (None, 0.05), 0.3),
        between(s["symbols"], None, (None, 0.02), 0.1),
        between(s["lines"], None, (None, 0.02), 0.3),
        between(s["word_size"], 2.5, (3.5, 9.0), 12.0),
        between(s["function_words"], 0.02, (0.08, None)),
        between(s["top_word"], None, (None, 0.12), 0.3),
    ]


@dataclass
class LabelModel:
    prior: float
    chance: np.ndarray  # labeller x class x vote

    def posterior(self, patterns: np.ndarray) -> np.ndarray:
        k = np.arange(patterns.shape[1])
        logs = np.stack([np.log(self.chance[k, c][k, patterns]).sum(axis=1) for c in (0, 1)], 1)
        odds = logs[:, 1] - logs[:, 0] + np.log(self.prior / (1 - self.prior))
        return 1 / (1 + np.exp(-np.clip(odds, -50, 50)))

    def accuracy(self) -> np.ndarray:
        """Share of right votes of each labeller when it votes."""
        right = self.prior * self.chance[:, 1, 1] + (1 - self.prior) * self.chance[:, 0, 0]
        votes_cast = right + self.prior * self.chance[:, 1, 0] + (1 - self.prior) * self.chance[:, 0, 1]
        return right / votes_cast


def fit_labels(patterns: np.ndarray, counts: np.ndarray, rounds: int = 200, tol: float = 1e-9, smooth: float = 1.0) -> LabelModel:
    """Expectation-maximisation from the share of good votes. A text with a bad vote starts as suspect."""
    good, bad = (patterns == 1).sum(axis=1), (patterns == 0).sum(axis=1)
    post = np.clip((good + 0.5) / (good + 3 * bad + 1.0), 0.02, 0.98)
    model, last = LabelModel(0.5, np.full((patterns.shape[1], 2, 3), 1 / 3)), -np.inf
    for _ in range(rounds):
        weight = np.stack([counts * (1 - post), counts * post], 1)
        chance = np.stack([[[weight[patterns[:, j] == v, c].sum() + smooth for v in range(3)] for c in (0, 1)] for j in range(patterns.shape[1])])
        chance /= chance.sum(axis=2, keepdims=True)
        prior = float(np.clip(weight[:, 1].sum() / max(counts.sum(), 1), 1e-3, 1 - 1e-3))
        model = LabelModel(prior, chance)
        post = model.posterior(patterns)
        k = np.arange(patterns.shape[1])
        like = sum(p * np.exp(np.log(chance[k, c][k, patterns]).sum(axis=1)) for c, p in ((0, 1 - prior), (1, prior)))
        now = float((counts * np.log(like)).sum())
        if now - last < tol * abs(now):
            break
        last = now
    return model


def hashed_statistics(s: dict[str, float]) -> list[int]:
    """Buckets of coarse statistics."""
    out = []
    for name in LABELLERS:
        x = s["words"] if name == "length" else s[name]
        level = int(np.log2(x + 1)) if name == "length" else int(min(x, 4.0) * (10 if name != "word_size" else 3))
        out.append(zlib.crc32(f"{name}={level}".encode()) % HASHED)
    return out


def word_buckets(words: list[str], known: dict[str, int]) -> np.ndarray:
    out = []
    for w in words:
        b = known.get(w)
        if b is None:
            b = zlib.crc32(w.encode("utf-8", "surrogatepass")) % HASHED
            if len(known) < CACHE_WORDS:
                known[w] = b
        out.append(b)
    return np.array(out, np.int64)


@dataclass
class LinearScorer:
    weight: np.ndarray
    bias: float

    def score(self, text: str | None, known: dict[str, int]) -> float:
        s = statistics(text)
        z = self.bias + self.weight[hashed_statistics(s)].sum()
        words = (text or "").lower().split()
        if words:
            z += self.weight[word_buckets(words, known)].mean()
        return float(1 / (1 + np.exp(-np.clip(z, -50, 50))))


def train_scorer(texts: list[str], soft: np.ndarray, steps: int = 120, rate: float = 0.1, ridge: float = 1e-5) -> LinearScorer:
    """Logistic regression on posterior labels, full-batch Adam, classes weighted alike."""
    if not texts:
        return LinearScorer(np.zeros(HASHED), 0.0)
    row, col, val = [], [], []
    for k, t in enumerate(texts):
        b, c = np.unique(word_buckets((t or "").lower().split(), {}), return_counts=True)
        s = hashed_statistics(statistics(t))
        row.append(np.full(len(b) + len(s), k))
        col.append(np.concatenate([b, s]))
        val.append(np.concatenate([c / max(c.sum(), 1), np.ones(len(s))]))
    row, col, val = np.concatenate(row), np.concatenate(col).astype(np.int64), np.concatenate(val)
    weight, bias, m, v = np.zeros(HASHED), 0.0, np.zeros(HASHED + 1), np.zeros(HASHED + 1)
    balance = soft / max(soft.sum(), 1e-9) + (1 - soft) / max((1 - soft).sum(), 1e-9)
    for t in range(1, steps + 1):
        z = bias + np.bincount(row, weight[col] * val, len(texts))
        g = (1 / (1 + np.exp(-np.clip(z, -50, 50))) - soft) * balance / 2
        grad = np.append(np.bincount(col, g[row] * val, HASHED) + ridge * weight, g.sum())
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        step = rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
        weight, bias = weight - step[:-1], bias - step[-1]
    return LinearScorer(weight, float(bias))


def vote_table(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cast = ["".join(map(str, votes(statistics(t.as_py())))) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(cast, pa.string())], ["doc_id", "votes"])

    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id bigint, votes string")


def classify(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", sample: int = SAMPLE, threshold: float = 0.5) -> DataFrame:
    """Per row: doc_id, votes, posterior (of the label model), score (of the scorer), kept."""
    spark, root = docs.sparkSession, scratch_root(docs.sparkSession)
    cast = stash(vote_table(docs, text_col, id_col), f"{root}/votes")
    counted = [(r.votes, r.n) for r in cast.groupBy("votes").agg(F.count(F.lit(1)).alias("n")).collect()]
    patterns = np.array([[int(c) for c in v] for v, _ in counted], np.int64).reshape(len(counted), len(LABELLERS))
    labels = fit_labels(patterns, np.array([n for _, n in counted], np.float64)) if counted else LabelModel(0.5, np.full((len(LABELLERS), 2, 3), 1 / 3))
    chosen = hash_sample(cast.where("doc_id is not null").select(F.col("doc_id").alias("id")), "id", sample)
    texts = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(chosen), "id")
    once = texts.groupBy("id").agg(F.min("text").alias("text")).collect()  # an id may repeat without bound
    learn = [r.text for r in sorted(once)]
    soft = labels.posterior(np.array([votes(statistics(t)) for t in learn], np.int64).reshape(len(learn), len(LABELLERS)))
    scorer = train_scorer([t or "" for t in learn], soft)
    weight, bias = scorer.weight.astype(np.float32), scorer.bias

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, known = LinearScorer(weight.astype(np.float64), bias), _shared("quality").setdefault("quality_words", {})
        for batch in batches:
            cast, score = [], []
            for t in batch.column(1):
                t = t.as_py()
                cast.append("".join(map(str, votes(statistics(t)))))
                score.append(own.score(t, known))
            post = labels.posterior(np.array([[int(c) for c in v] for v in cast], np.int64).reshape(len(cast), len(LABELLERS)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(cast, pa.string()), pa.array(post, pa.float64()), pa.array(score, pa.float64())], ["doc_id", "votes", "posterior", "score"])

    pairs = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    out = pairs.mapInArrow(run, "doc_id bigint, votes string, posterior double, score double")
    return out.withColumn("kept", F.col("score") >= threshold)
