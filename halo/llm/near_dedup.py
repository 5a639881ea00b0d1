"""Near-duplicate groups through a multi-index join on MinHash signatures, confirmed on full shingle sets.

A document is its set of distinct w-word shingles (64-bit hashes). Its signature is `coords` MinHash
values of 16 bits each, cut into `chunks` chunks. By the pigeonhole principle two signatures that differ
in at most chunks * (errors + 1) - 1 coordinates have a chunk with at most `errors` differences; the
index enumerates those errors by leaving out each set of `errors` coordinates of a chunk, so that pair
shares a key. With the production values (60 coordinates, 12 chunks of 5, 1 error) every pair of up to
23 differing coordinates is met, and a pair at similarity 0.8 misses all 12 chunks with probability
1e-7. A link needs the full sets.

Only components are wanted, so pairs inside a bucket are not all formed:
1. Documents with equal sets become one representative.
2. Star rounds: in each bucket all members are compared with one leader; confirmed links are contracted
   to components. Leaders are central documents, those whose keys many others share (the untouched
   original of a family links far more of its copies than a copy does), with jitter from round to round.
   Only buckets that still hold several components take part. A family collapses at linear cost.
3. The rest is exact without a row for any pair. Members of a bucket gather under its most central
   document; members outside the largest component of such a gathering are compared with all its members
   on full sets, in blocks of BLOCK by BLOCK documents spread over tasks, and only links come out.
Set sizes outside the ratio that the threshold allows are never compared. Links, components and sets stay
in tables; every round is written to the shared scratch folder.

Defined results: null or blank text has an empty set, size 0, and is its own component; a text of fewer
than w words is one shingle; rows that repeat an id repeat its text and share its component;
a null id is never linked; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from halo.llm.common import fresh_name, scratch_root, shuffle_partitions, stash
from halo.llm.tokenise import _shared

#: Ids of documents with candidate links up to this many (8 bytes each) are broadcast to the scan of texts.
BROADCAST_IDS = 2_000_000
WORD_CACHE = 250_000
#: Keys of more than 1 / HOT of the rows of a join by key are dealt over all its tasks: fewer than HOT keys.
HOT = 1000
#: Documents of a block in the comparisons that are left after the star rounds.
BLOCK = 2048

U = np.uint64
# Odd multipliers of the mixing function.
MIX_A, MIX_B, MIX_C = U(0x9E3779B97F4A7C15), U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB)


@dataclass(frozen=True)
class NearConfig:
    words: int = 5
    percent: int = 80
    coords: int = 60
    chunks: int = 12
    errors: int = 1
    seed: int = 20240229
    star_rounds: int = 2
    ascii_words: bool = True

    @property
    def guaranteed_distance(self) -> int:
        return self.chunks * (self.errors + 1) - 1

    @property
    def chunk_size(self) -> int:
        return self.coords // self.chunks


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of unsigned 64-bit integers."""
    x = (x ^ (x >> U(30))) * MIX_B
    x = (x ^ (x >> U(27))) * MIX_C
    return x ^ (x >> U(31))


def word_hashes(words: list[bytes]) -> np.ndarray:
    known = _shared("near").setdefault("word_hashes", {})
    try:
        return np.fromiter(map(known.__getitem__, words), U, len(words))
    except KeyError:
        room = WORD_CACHE - len(known)
        fresh = {w: xxhash.xxh64_intdigest(w) for w in set(words).difference(known)}
        if room > 0:
            known.update(x for x, _ in zip(fresh.items(), range(room)) if len(x[0]) <= 64)
        return np.fromiter((known[w] if w in known else fresh[w] for w in words), U, len(words))


def shingle_set(text: str | None, w: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the w-word shingles of an ASCII-lower-cased text."""
    words = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not words:
        return np.zeros(0, U)
    h = word_hashes(words)
    with np.errstate(over="ignore"):
        if len(h) < w:
            acc = np.array([len(h)], U) * MIX_A
            for x in h:
                acc = mix(acc ^ x) + MIX_A
            return acc
        n = len(h) - w + 1
        acc = np.full(n, U(w) * MIX_A, U)
        for k in range(w):
            acc = mix(acc ^ h[k : k + n]) + MIX_A
    return np.unique(acc)


def hash_functions(config: NearConfig) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.Generator(np.random.PCG64(config.seed))
    a = rng.integers(0, 2**63, config.coords, dtype=np.int64).astype(U) * U(2) + U(1)
    b = rng.integers(0, 2**63, config.coords, dtype=np.int64).astype(U)
    return a, b


def signature(s: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Low 16 bits of the MinHash values of a set."""
    best = np.full(len(a), np.iinfo(np.uint64).max, U)
    with np.errstate(over="ignore"):
        for k in range(0, len(s), 4096):
            part = s[k : k + 4096]
            h = part[None, :] * a[:, None] + b[:, None]
            h ^= h >> U(32)
            h *= MIX_B
            np.minimum(best, h.min(axis=1), out=best)
    return ((best >> U(24)) & U(0xFFFF)).astype(np.uint16)


def chunk_keys(sig: np.ndarray, config: NearConfig) -> np.ndarray:
    """The index keys of many signatures (rows): one column for each chunk and each set of coordinates kept."""
    t, keys = config.chunk_size, []
    with np.errstate(over="ignore"):
        for c in range(config.chunks):
            part = sig[:, c * t : (c + 1) * t].astype(U)
            for kept in combinations(range(t), t - config.errors):
                acc = np.full(len(sig), U(1 + c), U)
                for k in kept:
                    acc = mix(acc * MIX_A + part[:, k] + (U(k) << U(20)))
                keys.append(acc)
    return np.stack(keys, axis=1)


def _sketch(config: NearConfig):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b = hash_functions(config)
        for batch in batches:
            texts = batch.column(1)
            n, digest, sigs = [], [], []
            for k in range(len(texts)):
                s = shingle_set(texts[k].as_py(), config.words)
                n.append(len(s))
                digest.append(xxhash.xxh3_128_digest(s.tobytes()))
                sigs.append(signature(s, a, b).view(np.int64) if len(s) else None)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.array(sigs, pa.list_(pa.int64()))], ["doc_id", "n_shingles", "digest", "sig"])

    return run


def _keys(config: NearConfig):
    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                part = batch.slice(at, 4096)
                sig = part.column(2).flatten().to_numpy(zero_copy_only=False).view(np.uint16).reshape(part.num_rows, config.coords)
                keys = chunk_keys(sig, config)
                wide = keys.shape[1]
                ids = part.column(0).to_numpy(zero_copy_only=False)
                sizes = part.column(1).to_numpy(zero_copy_only=False)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, wide), pa.int64()), pa.array(np.repeat(sizes, wide), pa.int64()), pa.array(keys.reshape(-1).view(np.int64), pa.int64())], ["id", "n", "key"])

    return run


def _sets(words: int):
    def run(batches):
        for batch in batches:
            ids, texts = batch.column(0), batch.column(1)
            for at in range(0, batch.num_rows, 512):
                rows = [shingle_set(texts[k].as_py(), words).view(np.int64) for k in range(at, min(at + 512, batch.num_rows))]
                yield pa.RecordBatch.from_arrays([ids.slice(at, 512), pa.array(rows, pa.list_(pa.int64()))], ["id", "shingles"])

    return run


def sizes_allow(a: Column, b: Column, percent: int) -> Column:
    return (a * 100 >= b * percent) & (b * 100 >= a * percent)


def confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) whose full sets overlap enough."""
    left = sets.select(F.col("id").alias("a"), F.col("shingles").alias("_sa"))
    right = sets.select(F.col("id").alias("b"), F.col("shingles").alias("_sb"))
    both = pairs.select("a", "b").join(left, "a").join(right, "b")
    common = F.size(F.array_intersect("_sa", "_sb")).cast("bigint")
    union = F.size("_sa") + F.size("_sb") - common
    return both.where(common * 100 >= union * percent).select("a", "b")


def components(edges: DataFrame, root: str) -> DataFrame:
    """Label (the smallest id) of every vertex of `edges` (a, b): hook to the smallest neighbour, halve paths, contract.

    Each round hooks every vertex that has a smaller neighbour, follows parents to their roots by
    doubling, and goes on with the edges between roots, so the number of rounds is logarithmic.
    """
    links = stash(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct(), f"{root}/edges0")
    labels: DataFrame | None = None
    k = 0
    while not links.isEmpty():
        parent = stash(links.groupBy("b").agg(F.min("a").alias("p")).withColumnRenamed("b", "v"), f"{root}/parent{k}")
        hop = 0
        while True:  # double the paths until every parent is a root
            up = parent.select(F.col("v").alias("p"), F.col("p").alias("q"))
            moved = stash(parent.join(up, "p", "left").select("v", F.coalesce("q", "p").alias("p"), F.col("q").isNotNull().alias("moved")), f"{root}/parent{k}-{hop}")
            parent = moved.select("v", "p")
            if moved.where("moved").isEmpty():
                break
            hop += 1
        if labels is None:
            labels = parent
        else:
            up = parent.select(F.col("v").alias("p"), F.col("p").alias("q"))
            carried = labels.join(up, "p", "left").select("v", F.coalesce("q", "p").alias("p"))
            labels = stash(carried.unionByName(parent.join(labels.select("v"), "v", "left_anti")), f"{root}/labels{k}")
        to_a, to_b = parent.select(F.col("v").alias("a"), F.col("p").alias("pa")), parent.select(F.col("v").alias("b"), F.col("p").alias("pb"))
        joined = links.join(to_a, "a", "left").join(to_b, "b", "left")
        ends = joined.select(F.coalesce("pa", "a").alias("x"), F.coalesce("pb", "b").alias("y")).where("x <> y")
        k += 1
        links = stash(ends.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), f"{root}/edges{k}")
    if labels is None:
        return links.select(F.col("b").alias("v"), F.col("a").alias("label"))
    return labels.select("v", F.col("p").alias("label"))


def meet(rows: DataFrame, table: DataFrame, key: str, size: str) -> DataFrame:
    """`rows` (id, ...) joined by `key` with the stored `table`, one row a key, whose column `size` counts the rows that it meets.

    Rows of a hot key are dealt over the shuffle's partitions by id, and the key's row is copied to each. Hot keys, fewer
    than HOT, are a set of constants of the plan: rows are told apart without another join. The largest key is always
    among them, so the join is the same one in the plan of every table, and each row leaves it once at most.
    """
    n = shuffle_partitions(rows.sparkSession)
    total, largest = table.agg(F.sum(size), F.max(F.struct(size, key))).first()
    if largest is None:
        return rows.join(table, key)
    few = [r[0] for r in table.where(F.col(size) * HOT > F.lit(total)).select(key).collect()] or [largest[key]]
    hot = F.col(key).isin(few)
    dealt = rows.withColumn("_salt", F.when(hot, F.pmod(F.xxhash64("id"), F.lit(n)).cast("int")).otherwise(F.lit(0)))
    copies = table.withColumn("_salt", F.explode(F.when(hot, F.sequence(F.lit(0), F.lit(n - 1))).otherwise(F.array(F.lit(0)))))
    return dealt.join(copies, [key, "_salt"]).drop("_salt")


def _labelled(rows: DataFrame, labels: DataFrame | None) -> DataFrame:
    """`rows` (id, ...) with column c, the component so far."""
    if labels is None:
        return rows.withColumn("c", F.col("id"))
    return rows.join(labels.withColumnRenamed("v", "id"), "id", "left").withColumn("c", F.coalesce("label", "id")).drop("label")


def _sets_of(docs: DataFrame, ids: DataFrame, words: int, n_ids: int) -> DataFrame:
    ids = F.broadcast(ids) if n_ids <= BROADCAST_IDS else ids
    return docs.join(ids, "id", "left_semi").select("id", "text").mapInArrow(_sets(words), "id bigint, shingles array<bigint>")


def _block_links(percent: int):
    def run(table: pa.Table) -> pa.Table:
        role, ids, comp = (table.column(k).to_numpy() for k in ("role", "id", "c"))
        lists = table.column("shingles").combine_chunks()
        flat, ends = lists.flatten().to_numpy(), lists.offsets.to_numpy()
        ends = ends - ends[0]
        size = np.diff(ends)
        names, token = np.unique(flat, return_inverse=True)
        whole, side = np.flatnonzero(role == 0), np.flatnonzero(role == 1)
        a, b = [], []
        if len(whole) and len(side):
            tokens = np.concatenate([token[ends[k] : ends[k + 1]] for k in whole])
            starts = np.concatenate([[0], np.cumsum(size[whole])[:-1]])
            mark = np.zeros(len(names), np.int32)
            for k in side:
                mine = token[ends[k] : ends[k + 1]]
                mark[mine] = 1
                common = np.add.reduceat(mark[tokens], starts)
                mark[mine] = 0
                linked = (100 * common >= percent * (size[whole] + size[k] - common)) & (comp[whole] != comp[k])
                a.append(np.full(int(linked.sum()), ids[k]))
                b.append(ids[whole][linked])
        a, b = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (a, b))
        return pa.table({"a": pa.array(np.minimum(a, b), pa.int64()), "b": pa.array(np.maximum(a, b), pa.int64())})

    return run


def _block_compare(live: DataFrame, sets: DataFrame, percent: int, path: str) -> DataFrame:
    """Links between different components under one pivot, found block by block."""
    members = live.select(F.col("lead.id").alias("p"), "id", "c").distinct()
    counts = members.groupBy("p", "c").agg(F.count(F.lit(1)).alias("m"))
    main = counts.groupBy("p").agg(F.max_by("c", F.struct("m", "c")).alias("main"), F.max("m").alias("top"), F.sum("m").alias("all"), F.count(F.lit(1)).alias("k"))
    blocks = main.where("k > 1").select("p", "main", "all", F.ceil(F.col("all") / BLOCK).cast("int").alias("nw"), F.ceil((F.col("all") - F.col("top")) / BLOCK).cast("int").alias("ns"))
    known = stash(meet(members, stash(blocks, f"{path}-sizes"), "p", "all").drop("all"), path, "zstd")

    def dealt(own: str, own_n: str, other: str, other_n: str, role: int, rows: DataFrame) -> DataFrame:
        block = F.pmod(F.xxhash64("id"), F.col(own_n)).cast("int").alias(own)
        return rows.select("p", "id", "c", F.lit(role).alias("role"), block, F.explode(F.sequence(F.lit(0), F.col(other_n) - 1)).alias(other))

    cells = dealt("w", "nw", "s", "ns", 0, known).unionByName(dealt("s", "ns", "w", "nw", 1, known.where("c <> main")))
    return cells.join(sets, "id").groupBy("p", "w", "s").applyInArrow(_block_links(percent), "a bigint, b bigint")


def near_groups(docs: DataFrame, config: NearConfig = NearConfig(), text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """Per row of `docs`: doc_id, n_shingles, component_id, kept."""
    spark: SparkSession = docs.sparkSession
    root = scratch_root(spark)
    pairs = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string").alias("text"))
    sketches = stash(pairs.mapInArrow(_sketch(config), "doc_id bigint, n_shingles bigint, digest binary, sig array<bigint>"), f"{root}/sketches")
    full = sketches.where("n_shingles > 0 and doc_id is not null")
    reps = stash(full.groupBy("digest", "n_shingles").agg(F.min("doc_id").alias("id"), F.first("sig").alias("sig")), f"{root}/reps")
    # Two different sets are similar enough only if the smaller one is at least this large.
    able = reps.where(F.col("n_shingles") * 100 >= (F.col("n_shingles") + 1) * config.percent)
    keyed = able.select("id", F.col("n_shingles").alias("n"), "sig").mapInArrow(_keys(config), "id bigint, n bigint, key bigint")
    # Keys that one representative alone has cannot link it.
    common = stash(keyed.groupBy("key").agg(F.count(F.lit(1)).alias("m")).where("m > 1"), f"{root}/common", "zstd")
    index = stash(meet(keyed, common, "key", "m"), f"{root}/index", "zstd")
    # How many others share the keys of a document: central members of a family have the most.
    central = stash(index.groupBy("id").agg(F.sum("m").cast("double").alias("central")), f"{root}/central")
    edges, labels, sets, seen = [], None, None, None
    sets = stash(_sets_of(pairs, central.select("id"), config.words, central.count()), f"{root}/sets")
    live = index.join(central, "id").select("id", "n", "key", "central")
    for r in range(config.star_rounds + 1):
        rows = _labelled(live, labels)
        last = r == config.star_rounds
        jitter = F.pmod(F.xxhash64("id", F.lit(r)), F.lit(1000)) / 1000.0
        rank = F.col("central") if last else F.col("central") * (1.0 - (0.3 * min(r, config.star_rounds - 1)) * jitter)
        per = rows.groupBy("key").agg(F.count(F.lit(1)).alias("_m"), F.min("c").alias("_lo"), F.max("c").alias("_hi"), F.max_by(F.struct("id", "n", "c"), F.struct(rank, F.col("id"))).alias("lead"))
        mixed = stash(per.where("_lo < _hi").select("key", "lead", "_m"), f"{root}/mixed{r}", "zstd")
        live_rows = stash(meet(rows, mixed, "key", "_m").drop("_m"), f"{root}/live{r}", "zstd")
        if live_rows.isEmpty():
            break
        near = live_rows.where((F.col("c") != F.col("lead.c")) & sizes_allow(F.col("n"), F.col("lead.n"), config.percent))
        made = near.select(F.least("id", "lead.id").alias("a"), F.greatest("id", "lead.id").alias("b"))
        made = made.distinct()
        if seen is not None:
            made = made.join(seen, ["a", "b"], "left_anti")
        made = stash(made, f"{root}/pairs{r}")
        seen = made if seen is None else seen.unionByName(made)
        found = [] if made.isEmpty() else [confirm(made, sets, config.percent)]
        found += [_block_compare(live_rows, sets, config.percent, f"{root}/pivots")] if last else []
        if found:
            links = found[0] if len(found) == 1 else found[0].unionByName(found[1])
            edges.append(stash(links.distinct(), f"{root}/links{r}"))
            every = edges[0]
            for e in edges[1:]:
                every = every.unionByName(e)
            labels = stash(components(every, f"{root}/cc{r}"), f"{root}/labels{r}")
        live = live_rows.select("id", "n", "key", "central")
    named = _labelled(reps.select("id", "digest", "n_shingles"), labels).select("digest", "n_shingles", F.col("c").alias("_c"))
    joined = sketches.select("doc_id", "n_shingles", "digest").join(named, ["digest", "n_shingles"], "left")
    own = (F.col("n_shingles") == 0) | F.col("doc_id").isNull() | F.col("_c").isNull()
    out = joined.select("doc_id", "n_shingles", F.when(own, F.col("doc_id")).otherwise(F.col("_c")).alias("component_id"))
    return out.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def keep_one(docs: DataFrame, groups: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """`docs` without the rows whose group keeps another one. Only ids of dropped rows are joined."""
    own_id = fresh_name(docs.columns, "id")
    gone = groups.where("not kept").select(F.col("doc_id").alias(own_id)).distinct()
    return docs.join(gone, F.col(id_col).cast("bigint") == F.col(own_id), "left_anti")
