"""N-gram Jaccard join: MinHash banding, then verification on full n-gram sets.

1. Every text becomes the set of its word n-grams (64-bit hashes of five lower-cased, white-space separated
   words; a shorter text is one n-gram). Texts with equal sets form one node, counted, not paired.
2. Nodes are dealt by band hashes. The members of a band bucket are tied to its smallest member only; the
   components of these ties are candidate groups: every pair that shares a bucket lies in one group.
3. The full sets of a group meet in one task, or, for a large group, in one task for each pair of its
   blocks. All pairs of nodes with a Jaccard similarity of at least the threshold are links. What leaves a task is a
   count of links for each node and a spanning forest, never the pairs.

Bands and rows come from the target recall: the most rows whose bands fit the number of hashes.
A pair that no band catches is still found when others tie it into the group, so recall is above the target.

Result: one row for every input row: doc_id, class_id (smallest doc_id of the documents linked to it,
directly or through others), copy_class (smallest doc_id with the same n-gram set), n_links (other documents
with a similarity of at least the threshold, copies included), n_shingles.

Defined results: null text and text without a word have no n-grams, no links and their own class; repeated rows are copies of
each other; ties go to the smallest doc_id; an empty table gives an empty table; other columns are ignored.
"""

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .components import connected_components

WORDS = 5
THRESHOLD = 0.8
RECALL = 0.999
MAX_HASHES = 320
#: Nodes of one side of a verification task.
BLOCK_NODES = 256
CACHE_WORDS = 500_000
MIX = np.uint64(0x9E3779B97F4A7C15)
#: N-grams hashed side by side, so that they stay in the processor's cache.
SLICE = 1 << 15


def banding(threshold: float = THRESHOLD, recall: float = RECALL, max_hashes: int = MAX_HASHES) -> tuple[int, int]:
    """(bands, rows): the most rows for which some number of bands reaches the recall at the threshold within max_hashes."""
    best = (max_hashes, 1)
    for rows in range(1, 65):
        bands = math.ceil(math.log(1 - recall) / math.log(1 - threshold**rows))
        if bands * rows <= max_hashes:
            best = (bands, rows)
    return best


class WordHashes(dict):
    def __missing__(self, word: str) -> int:
        if len(self) >= CACHE_WORDS:
            self.clear()
        h = self[word] = xxhash.xxh64_intdigest(word.encode("utf-8", "surrogatepass"))
        return h


def finish(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * MIX
    return x ^ (x >> np.uint64(29))


def shingles(text, n: int = WORDS) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word n-grams."""
    cache = common.process_cache("words")
    words = (text or "").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    hashes = cache.setdefault("hashes", WordHashes())
    w = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
    k = min(n, len(w))
    h = np.full(len(w) - k + 1, np.uint64(k))
    for i in range(k):
        h = h * MIX + w[i:len(w) - k + 1 + i]
    return np.unique(finish(h))


def band_hashes(sets: list[np.ndarray], bands: int, rows: int, seed: int = 1) -> np.ndarray:
    """(texts, bands) hashes; every set must have a member."""
    rng = np.random.default_rng(seed)
    a = (rng.integers(0, 2**31, bands * rows, dtype=np.uint64) * 2 + 1).astype(np.uint32)
    b = rng.integers(0, 2**32, bands * rows, dtype=np.uint64).astype(np.uint32)
    out = np.empty((len(sets), bands), np.uint64)
    start = 0
    while start < len(sets):
        end, size = start, 0
        while end < len(sets) and (end == start or size + len(sets[end]) <= SLICE):
            size += len(sets[end])
            end += 1
        x = (np.concatenate(sets[start:end]) >> np.uint64(32)).astype(np.uint32)
        first = np.concatenate(([0], np.cumsum([len(s) for s in sets[start:end - 1]], dtype=np.int64))) if end - start > 1 else np.zeros(1, np.int64)
        t = np.empty_like(x)
        for band in range(bands):
            h = np.full(end - start, np.uint64(band + 1))
            for i in range(band * rows, (band + 1) * rows):
                np.multiply(x, a[i], out=t)
                t += b[i]
                h = h * MIX + np.minimum.reduceat(t, first)
            out[start:end, band] = finish(h)
        start = end
    return out


def signatures(docs: DataFrame, n: int, bands: int, rows: int) -> DataFrame:
    """doc_id, n_shingles, node (hash of the set; null without n-grams), bands."""

    def run(batch: pa.RecordBatch):
        sets = [shingles(t, n) for t in common.texts_of(batch)]
        some = [i for i, s in enumerate(sets) if len(s)]
        made = band_hashes([sets[i] for i in some], bands, rows).view(np.int64) if some else None
        node, of = [None] * len(sets), [None] * len(sets)
        for k, i in enumerate(some):
            node[i] = node_of(sets[i])
            of[i] = made[k]
        return {"doc_id": common.column_of(batch, "doc_id"), "n_shingles": [len(s) for s in sets], "node": node, "bands": of}

    return common.arrow_map(docs.select("doc_id", "text"), run, "doc_id long, n_shingles long, node long, bands array<long>")


def node_of(s: np.ndarray) -> int:
    h = xxhash.xxh3_64_intdigest(s.tobytes())
    return h - 2**64 if h >= 2**63 else h


def links_within(sets: list, nodes: list, copies: list, side: list | None, threshold: float):
    """(links of each node, root of each node in the spanning forest). side: None for all pairs, else 0 and 1 for pairs across."""
    m = len(sets)
    links, parent = [0] * m, list(range(m))

    def root(i):
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    sizes = np.array([len(s) for s in sets])
    flat = np.concatenate(sets)
    ids = np.unique(flat, return_inverse=True)[1]
    first = np.cumsum(sizes) - sizes
    mark = np.zeros(int(ids.max()) + 1, np.int32)
    weight = np.array(copies)
    for i in range(m):
        own = ids[first[i]:first[i] + sizes[i]]
        mark[own] = 1
        lo = i + 1 if side is None else (sum(s == 0 for s in side) if side[i] == 0 else m)
        if lo < m:
            both = np.add.reduceat(mark[ids[first[lo]:]], first[lo:] - first[lo])
            hit = np.flatnonzero(both >= threshold * (sizes[i] + sizes[lo:] - both) - 1e-9) + lo
            if len(hit):
                links[i] += int(weight[hit].sum())
                for j in hit.tolist():
                    links[j] += copies[i]
                    a, b = root(i), root(j)
                    if nodes[a] < nodes[b]:
                        parent[b] = a
                    elif a != b:
                        parent[a] = b
        mark[own] = 0
    return links, [nodes[root(i)] for i in range(m)]


def verified(members: DataFrame, n: int, threshold: float) -> DataFrame:
    """node, root, links, split for each node and task. members: grp, nb, lo, hi, blk, node, copies, text."""
    schema = "node long, root long, links long, split boolean"
    dealt = members.repartition("grp", "lo", "hi").sortWithinPartitions("grp", "lo", "hi", "blk", "node")

    def run(batches):
        key, rows, out = None, {}, []

        def close():
            lo, hi = key[1], key[2]
            nodes = list(rows)
            sets = [rows[x][0] for x in nodes]
            side = None if lo == hi else [0 if rows[x][2] == lo else 1 for x in nodes]
            links, roots = links_within(sets, nodes, [rows[x][1] for x in nodes], side, threshold)
            out.extend(zip(nodes, roots, links, [key[3] > 1] * len(nodes), strict=True))

        def batch_of():
            cols = list(zip(*out, strict=True))
            out.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.bool_()), strict=True)], names=["node", "root", "links", "split"])

        for batch in batches:
            cols = [common.column_of(batch, c).to_pylist() for c in ("grp", "nb", "lo", "hi", "blk", "node", "copies", "text")]
            for grp, nb, lo, hi, blk, node, copies, text in zip(*cols, strict=True):
                if key != (grp, lo, hi, nb):
                    if rows:
                        close()
                    key, rows = (grp, lo, hi, nb), {}
                if node not in rows:
                    s = shingles(text, n)
                    if node_of(s) == node:
                        rows[node] = (s, copies, blk)
            if len(out) > 10_000:
                yield batch_of()
        if rows:
            close()
        if out:
            yield batch_of()

    return dealt.mapInArrow(run, schema)


def jaccard_join(docs: DataFrame, *, n: int = WORDS, threshold: float = THRESHOLD, recall: float = RECALL, max_hashes: int = MAX_HASHES, block_nodes: int = BLOCK_NODES) -> DataFrame:
    bands, rows = banding(threshold, recall, max_hashes)
    docs = docs.select("doc_id", "text")
    signed = common.stored(signatures(docs, n, bands, rows), "signatures")
    nodes = signed.filter("node is not null").groupBy("node").agg(F.min("doc_id").alias("copy_class"), F.count(F.lit(1)).alias("copies"), F.first("bands").alias("bands"))
    nodes = common.stored(nodes, "nodes")
    by_band = nodes.select("node", F.explode("bands").alias("band"))
    shared = by_band.groupBy("band").agg(F.min("node").alias("m"), F.count(F.lit(1)).alias("c")).filter("c > 1").drop("c")
    ties = by_band.join(shared, "band").filter("node <> m").select(F.col("node").alias("u"), F.col("m").alias("v"))
    groups = common.stored(connected_components(ties).withColumnRenamed("comp", "grp"), "groups")
    blocks = groups.groupBy("grp").agg(F.ceil(F.count(F.lit(1)) / block_nodes).cast("int").alias("nb"))
    placed = groups.join(blocks, "grp").join(nodes.select("node", "copy_class", "copies"), "node")
    placed = placed.withColumn("blk", F.pmod(F.xxhash64("node"), F.col("nb")).cast("int"))
    texts = placed.join(docs, placed["copy_class"].eqNullSafe(docs["doc_id"])).select("grp", "nb", "blk", "node", "copies", "text")
    other = F.explode(F.sequence(F.lit(0), F.col("nb") - 1))
    members = texts.withColumn("o", other).select("grp", "nb", F.least("blk", "o").alias("lo"), F.greatest("blk", "o").alias("hi"), "blk", "node", "copies", "text")
    found = common.stored(verified(members, n, threshold), "links")
    links = found.groupBy("node").agg(F.sum("links").alias("links"))
    whole = found.filter("not split").select("node", F.col("root").alias("comp"))
    crossing = found.filter("split and node <> root").select(F.col("node").alias("u"), F.col("root").alias("v"))
    comps = whole if crossing.isEmpty() else whole.unionByName(connected_components(crossing).select("node", "comp"))
    table = nodes.select("node", "copy_class", "copies").join(links, "node", "left").join(comps, "node", "left")
    table = table.select("node", "copy_class", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("comp", "node").alias("comp"))
    smallest = table.groupBy("comp").agg(F.min("copy_class").alias("class_id"))
    table = table.join(smallest, "comp").select("node", "copy_class", "n_links", "class_id")
    out = signed.select("doc_id", "n_shingles", "node").join(table, "node", "left")
    return out.select(
        "doc_id", F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"),
        F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("copy_class")).alias("copy_class"), F.coalesce("n_links", F.lit(0)).alias("n_links"), "n_shingles")


def drop_near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """The rows of docs with one document of each class (the smallest doc_id), all columns."""
    one, same = common.spare(docs, "keep"), common.spare(docs, "text")
    keep = jaccard_join(docs, **options).filter(F.col("doc_id").eqNullSafe(F.col("class_id"))).select(F.col("doc_id").alias(one)).distinct()
    kept = docs.join(keep, docs["doc_id"].eqNullSafe(keep[one]), "left_semi")
    return kept.withColumn(same, F.xxhash64("text")).dropDuplicates(["doc_id", same]).drop(same)


def op1_ngram_jaccard_join(spark, sf_dir):
    return jaccard_join(common.documents(spark, sf_dir))
