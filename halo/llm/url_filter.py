"""URL filtering: host and path rules first, gradient-boosted trees on lexical features for the rest.

Features of a URL: lengths, depth, shares of digits and hyphens, character entropy, parameter counts,
and statistics of its host's suffixes (block rate among the labelled URLs, smoothed, out of fold while
learning). Suffixes are counted over all distinct labelled URLs and joined to the pages. Trees are grown on
quantile bins by Newton gain with logistic loss, on a bounded sample: SAMPLE distinct URLs with the smallest
hash. Labels come from a column expression; the default marks hosts one of whose words (parts between dots and
hyphens, digits at their end aside) is among SEED_TERMS, a blocklist. Every URL is judged.

Defined results: a null URL, or one without "://", has an empty host and path, no rule, and the score
of an empty URL; rows that repeat a page are judged each; with one class only among the labels every
URL gets that class's rate; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from halo.llm.common import ASCII_LOWER, ASCII_UPPER, hash_sample, stash

SAMPLE = 20_000
HOT = 1000  # keys of more than 1 / HOT of a join's rows are broadcast: fewer than HOT keys
FOLDS = ("b0", "s0", "b1", "s1")  # blocked and seen URLs of both folds
LEVELS = [f"{c}_{k}" for k in (1, 2, 3) for c in FOLDS]
# Words of hosts that the default labels block.
SEED_TERMS = ("adult", "ads", "bets", "casino", "cheap", "malware", "phish", "pills", "porn", "spam", "track", "viagra", "warez", "xxx")


def host_path(url: Column) -> tuple[Column, Column]:
    after = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url)))
    after = F.coalesce(after, F.lit(""))
    host = F.regexp_extract(after, "^[^/?#]*", 0)
    path = F.regexp_extract(F.substring(after, F.length(host) + 1, F.length(after)), "^[^?#]*", 0)
    return F.translate(host, ASCII_UPPER, ASCII_LOWER), path


def rule_match(host: Column, path: Column, rules: list[tuple[str, str]]) -> Column:
    """The longest rule (text, verdict) that fits, or null."""
    out = F.lit(None).cast("string")
    for text, _ in sorted(rules, key=lambda r: (len(r[0]), r[0])):  # the longest is tested first
        h, slash, p = text.partition("/")
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(slash + p)
        out = F.when(fits, F.lit(text)).otherwise(out)
    return out


def verdict_of(rule: Column, rules: list[tuple[str, str]]) -> Column:
    out = F.lit(None).cast("string")
    for text, verdict in rules:
        out = F.when(rule == text, F.lit(verdict)).otherwise(out)
    return out


def suffixes(host: str) -> list[str]:
    parts = host.split(".")
    return [".".join(parts[-k:]) for k in (1, 2, 3) if len(parts) >= k]


def features(url: str | None) -> tuple[list[float], list[str]]:
    u = url or ""
    at = u.find("://")
    after = u[at + 3 :] if at >= 0 else ""
    cut = min((k for k in (after.find(c) for c in "/?#") if k >= 0), default=len(after))
    host, rest = after[:cut].lower(), after[cut:]
    query = rest.partition("?")[2].partition("#")[0]
    path = rest.partition("?")[0].partition("#")[0]
    n = max(len(u), 1)
    counts = Counter(u)
    entropy = -sum(c / n * math.log2(c / n) for c in counts.values()) if u else 0.0
    label = max(host.split("."), key=len) if host else ""
    hn = max(len(host), 1)
    vowels = sum(c in "aeiou" for c in label)
    return [
        len(u), len(host), len(path), len(query), path.count("/"), host.count("."), sum(c.isdigit() for c in u) / n, host.count("-"),
        sum(c.isdigit() for c in host) / hn, entropy, query.count("=") + (query.count("&") if query else 0), float("#" in rest), float(u.startswith("https")),
        len(label), vowels / max(len(label), 1), len(set(host)) / hn,
    ], suffixes(host)


@dataclass
class SuffixStats:
    """Smoothed share of blocked URLs under each suffix."""

    prior: float = 0.0
    blocked: dict[str, float] = field(default_factory=dict)
    seen: dict[str, int] = field(default_factory=dict)

    @staticmethod
    def fit(keys: list[list[str]], y: np.ndarray) -> "SuffixStats":
        blocked, seen = defaultdict(float), defaultdict(int)
        for ks, label in zip(keys, y.tolist()):
            for k in ks:
                blocked[k] += label
                seen[k] += 1
        return SuffixStats(float(y.mean()) if len(y) else 0.0, dict(blocked), dict(seen))

    def columns(self, keys: list[list[str]], strength: float = 4.0) -> np.ndarray:
        out = np.empty((len(keys), 4))
        for r, ks in enumerate(keys):
            rates = [(self.blocked.get(k, 0.0) + strength * self.prior) / (self.seen.get(k, 0) + strength) for k in ks]
            rates = (rates + [self.prior] * 3)[:3]
            out[r] = [*rates, math.log1p(self.seen.get(ks[-1], 0)) if ks else 0.0]
        return out


def suffix_columns(labels: np.ndarray, blocked: np.ndarray, seen: np.ndarray, prior: float, strength: float = 4.0) -> np.ndarray:
    """SuffixStats.columns from counts (row, suffix length) of hosts with `labels` labels."""
    has = np.arange(1, 4) <= labels[:, None]
    rates = np.where(has, (blocked + strength * prior) / (seen + strength), prior)
    deepest = seen[np.arange(len(seen)), np.clip(labels, 1, 3) - 1]
    return np.hstack([rates, np.log1p(deepest)[:, None]])


def suffix_key(url: Column) -> Column:
    """The last three labels of the host: every suffix that is counted follows from it."""
    return F.substring_index(host_path(url)[0], ".", -3)


def fold_of(url: Column) -> Column:
    return F.pmod(F.crc32(url.cast("binary")), F.lit(2))


def attach(rows: DataFrame, counts: DataFrame, key: str) -> DataFrame:
    """`rows` with the columns of `counts` by `key`, null where it has none; `parts` counts the rows that a key meets."""
    total = counts.agg(F.sum("parts")).first()[0] or 0
    hot = F.col("parts") > total / HOT
    few = F.broadcast(counts.where(hot).drop("parts"))
    rest = counts.where(~hot).drop("parts").hint("merge")
    met = rows.join(few, key)
    return met.unionByName(rows.join(few.select(key), key, "left_anti").join(rest, key, "left").select(met.columns))


@dataclass
class CorpusCounts:
    """Counts of all distinct labelled URLs: `rows` holds those of the three suffixes of every suffix_key, `total` the sums by FOLDS."""

    rows: DataFrame
    total: np.ndarray

    def prior(self, folds: tuple[int, ...] = (0, 1)) -> float:
        return float(sum(self.total[2 * f] for f in folds) / max(sum(self.total[2 * f + 1] for f in folds), 1))

    def columns(self, keys: list[str], counts: np.ndarray, folds: tuple[int, ...] = (0, 1)) -> np.ndarray:
        """Features from rows of LEVELS, by the URLs of `folds`."""
        if np.isnan(counts).any():
            raise ValueError("a host has no counts: they must come from the pages that are judged")
        by_level = counts.reshape(len(counts), 3, 4)
        blocked, seen = (sum(by_level[:, :, 2 * f + k] for f in folds) for k in (0, 1))
        return suffix_columns(np.array([k.count(".") + 1 for k in keys], int), blocked, seen, self.prior(folds))


def corpus_counts(pages: DataFrame, label: Column, root: str, url_col: str = "url") -> CorpusCounts:
    """Each distinct URL counts once, with its smallest label; a null URL or label counts nowhere. Longer suffixes are summed into shorter ones."""
    rows = pages.select(F.col(url_col).cast("string").alias("u"), label.cast("double").alias("y"))
    once = rows.groupBy("u").agg(F.min("y").alias("y"), F.count(F.lit(1)).alias("parts"))
    of = [F.when(F.col("u").isNotNull() & (fold_of(F.col("u")) == f), F.col("y")) for f in (0, 1)]
    sums = [e.cast("double").alias(c) for c, e in zip(FOLDS, (F.coalesce(F.sum(of[0]), F.lit(0.0)), F.count(of[0]), F.coalesce(F.sum(of[1]), F.lit(0.0)), F.count(of[1])))]
    level = {3: stash(once.groupBy(suffix_key(F.col("u")).alias("key_3")).agg(F.sum("parts").alias("parts"), *sums), f"{root}/suffix-3")}
    for k in (2, 1):
        shorter = F.substring_index(f"key_{k + 1}", ".", -k).alias(f"key_{k}")
        level[k] = stash(level[k + 1].groupBy(shorter).agg(F.count(F.lit(1)).alias("parts"), *[F.sum(c).alias(c) for c in FOLDS]), f"{root}/suffix-{k}")
    named = {k: t.withColumnsRenamed({c: f"{c}_{k}" for c in FOLDS}) for k, t in level.items()}
    out = named[1]
    for k in (2, 3):
        longer = named[k].withColumn(f"key_{k - 1}", F.substring_index(f"key_{k}", ".", 1 - k))
        out = stash(attach(longer, out, f"key_{k - 1}").drop(f"key_{k - 1}"), f"{root}/suffixes-to-{k}")
    total = level[1].agg(*[F.sum(c) for c in FOLDS]).first()
    return CorpusCounts(out.withColumnRenamed("key_3", "suffix_key"), np.array([x or 0.0 for x in total]))


class BoostedTrees:
    """Binary logistic gradient boosting on quantile bins, depth-limited trees as flat arrays."""

    def __init__(self, trees: int = 40, depth: int = 4, rate: float = 0.2, bins: int = 32, least: float = 2.0, ridge: float = 1.0):
        self.shape = (trees, depth, rate, bins, least, ridge)
        self.base = 0.0
        self.edges: list[np.ndarray] = []
        self.nodes: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []  # feature, cut bin, value; children of i: 2i+1, 2i+2

    def _bin(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(self.edges)], 1) if len(x) else np.zeros((0, len(self.edges)), int)

    def fit(self, x: np.ndarray, y: np.ndarray) -> "BoostedTrees":
        trees, depth, rate, bins, least, ridge = self.shape
        self.edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1], method="lower")) for j in range(x.shape[1])]
        mean = float(np.clip(y.mean(), 1e-4, 1 - 1e-4))
        self.base = math.log(mean / (1 - mean))
        b, f = self._bin(x), np.full(len(y), self.base)
        size = 2 ** (depth + 1) - 1
        for _ in range(trees if 0 < y.mean() < 1 else 0):
            p = 1 / (1 + np.exp(-f))
            g, h = y - p, p * (1 - p)
            feature, cut, value, node = np.full(size, -1), np.zeros(size, int), np.zeros(size), np.zeros(len(y), int)
            for k in range(size):
                rows = np.flatnonzero(node == k)
                if not len(rows):
                    continue
                gs, hs = g[rows].sum(), h[rows].sum()
                value[k] = rate * gs / (hs + ridge)
                if k >= 2**depth - 1 or hs < 2 * least * 0.1:
                    continue
                best = (1e-6, -1, 0)
                for j in range(b.shape[1]):
                    m = len(self.edges[j]) + 1
                    gl = np.cumsum(np.bincount(b[rows, j], g[rows], m))[:-1]
                    hl = np.cumsum(np.bincount(b[rows, j], h[rows], m))[:-1]
                    if not len(gl):
                        continue
                    gain = gl**2 / (hl + ridge) + (gs - gl) ** 2 / (hs - hl + ridge) - gs**2 / (hs + ridge)
                    c = int(np.argmax(gain))
                    if gain[c] > best[0]:
                        best = (float(gain[c]), j, c)
                if best[1] >= 0:
                    feature[k], cut[k] = best[1], best[2]
                    node[rows] = 2 * k + 1 + (b[rows, best[1]] > best[2])
            self.nodes.append((feature, cut, value))
            f += self._tree(b, self.nodes[-1])
        return self

    def _tree(self, b: np.ndarray, tree) -> np.ndarray:
        feature, cut, value = tree
        node = np.zeros(len(b), int)
        for _ in range(self.shape[1]):
            inner = feature[node] >= 0
            right = b[np.arange(len(b)), np.maximum(feature[node], 0)] > cut[node]
            node = np.where(inner, 2 * node + 1 + right, node)
        return value[node]

    def predict(self, x: np.ndarray) -> np.ndarray:
        b = self._bin(x)
        return 1 / (1 + np.exp(-(self.base + sum((self._tree(b, t) for t in self.nodes), np.zeros(len(b))))))


@dataclass
class UrlModel:
    stats: SuffixStats
    trees: BoostedTrees

    @staticmethod
    def train(urls: list[str], labels: list[int]) -> "UrlModel":
        y = np.asarray(labels, np.float64)
        rows = [features(u) for u in urls]
        if not rows:
            return UrlModel(SuffixStats(), BoostedTrees(trees=0).fit(np.zeros((1, 20)), np.zeros(1)))
        keys = [k for _, k in rows]
        half = np.arange(len(y)) % 2
        lexical, out_of_fold = np.array([f for f, _ in rows]), np.zeros((len(y), 4))
        for fold in (0, 1):
            other = SuffixStats.fit([k for k, m in zip(keys, half) if m != fold], y[half != fold])
            out_of_fold[half == fold] = other.columns([k for k, m in zip(keys, half) if m == fold])
        return UrlModel(SuffixStats.fit(keys, y), BoostedTrees().fit(np.hstack([lexical, out_of_fold]), y))

    @staticmethod
    def train_on_corpus(sample: DataFrame, counts: CorpusCounts) -> "UrlModel":
        """Trees from a bounded `sample` (u, y); a URL's suffix features come from the fold of the corpus that it is not in."""
        named = sample.withColumn("suffix_key", suffix_key(F.col("u"))).withColumn("fold", fold_of(F.col("u")))
        rows = attach(named, counts.rows, "suffix_key").orderBy(F.xxhash64("u"), "u").collect()
        if not rows:
            return UrlModel.train([], [])
        lexical, fold = np.array([features(r.u)[0] for r in rows]), np.array([r.fold for r in rows])
        keys, levels = np.array([r.suffix_key for r in rows], object), np.array([[r[c] for c in LEVELS] for r in rows], np.float64)
        suffix = np.empty((len(rows), 4))
        for f in (0, 1):
            suffix[fold == f] = counts.columns(keys[fold == f].tolist(), levels[fold == f], (1 - f,))
        y = np.array([r.y for r in rows], np.float64)
        return UrlModel(SuffixStats(counts.prior()), BoostedTrees().fit(np.hstack([lexical, suffix]), y))

    def score(self, urls: list[str | None], suffix: np.ndarray | None = None) -> np.ndarray:
        """`suffix`: the suffix features where they come from CorpusCounts."""
        rows = [features(u) for u in urls]
        if not rows:
            return np.zeros(0)
        return self.trees.predict(np.hstack([np.array([f for f, _ in rows]), self.stats.columns([k for _, k in rows]) if suffix is None else suffix]))


def seed_label(url: Column) -> Column:
    host, _ = host_path(url)
    return host.rlike(r"(^|[.\-])(" + "|".join(SEED_TERMS) + r")[0-9]*([.\-]|$)").cast("int")


def sample_rows(pages: DataFrame, label: Column, url_col: str = "url", most: int = SAMPLE) -> DataFrame:
    """At most `most` distinct labelled URLs (u, y), those with the smallest hash."""
    rows = pages.select(F.col(url_col).cast("string").alias("u"), label.alias("y")).where("u is not null and y is not null")
    return hash_sample(rows, "u", most)


def labelled_sample(pages: DataFrame, label: Column, url_col: str = "url", most: int = SAMPLE) -> tuple[list[str], list[int]]:
    got = sample_rows(pages, label, url_col, most).collect()
    return [r.u for r in got], [r.y for r in got]


def judge(pages: DataFrame, rules: list[tuple[str, str]], model: UrlModel, url_col: str = "url", id_col: str = "page_id", threshold: float = 0.5, counts: CorpusCounts | None = None) -> DataFrame:
    """Per row: page_id, host, path, rule, verdict, score (that of the trees). `counts` are those of the same pages, for a model trained on them."""
    columns = None if counts is None else CorpusCounts(None, counts.total).columns  # workers get no DataFrame

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            suffix = None
            if columns is not None:
                levels = [batch.column(c).to_numpy(zero_copy_only=False).astype(np.float64) for c in LEVELS]
                suffix = columns(batch.column("suffix_key").to_pylist(), np.stack(levels, 1))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(model.score(batch.column(1).to_pylist(), suffix), pa.float64())], ["page_id", "url", "score"])

    given = pages.select(F.col(id_col).cast("bigint").alias("page_id"), F.col(url_col).cast("string").alias("url"))
    if counts is not None:
        given = attach(given.withColumn("suffix_key", suffix_key(F.col("url"))), counts.rows, "suffix_key").select("page_id", "url", "suffix_key", *LEVELS)
    scored = given.mapInArrow(run, "page_id bigint, url string, score double")
    host, path = host_path(F.col("url"))
    named = scored.withColumn("host", host).withColumn("path", path).withColumn("rule", rule_match(F.col("host"), F.col("path"), rules))
    by_model = F.when(F.col("score") >= threshold, F.lit("block")).otherwise(F.lit("allow"))
    return named.select("page_id", "host", "path", "rule", F.coalesce(verdict_of(F.col("rule"), rules), by_model).alias("verdict"), "score")
