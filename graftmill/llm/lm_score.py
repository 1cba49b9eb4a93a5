"""Stupid-backoff scores of documents from n-gram count tables of the whole corpus.

Relations: (document, position, n-gram), (n-gram, count), and their join, summed per document. Rows are packed: a
*block* is a set of documents that fits a task, and the distinct n-grams of a block travel as sorted arrays of 64-bit
hashes, one for each bucket of the count table. So an n-gram moves once for each block that holds it, however
often it occurs there, and the count table is partitioned by hash:

    documents --by block--> distinct n-grams --by bucket--> counts over all blocks --by block--> scores

Unigrams and bigrams are counted first. A longer n-gram is sent only where both n-grams one shorter in it occur outside the document, which
is exact: otherwise its own count there is 0.

A document is scored against all others: its own occurrences are taken off every count. At each position the longest
n-gram that occurs elsewhere gives count(n-gram) / count(its first words), times ALPHA for each step back; a word that occurs
nowhere else counts as seen once and takes one more step. Words are lower-cased and separated by white space.

Result: doc_id, n_words, mean_log (mean natural logarithm over the words, 6 digits; null without a word).

Defined results: null and empty text have no words; a repeated row is a document of its own and so supports its twin; an empty
table gives an empty table; other columns are ignored.
"""

import re

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

ALPHA = 0.4
ORDER = 3
#: Text of a block, and of the input for each bucket of the count table: they bound a task's memory. Larger inputs take larger ones, so that a
#: block's share of a bucket stays long.
BLOCK_BYTES = 6_000_000
BUCKET_BYTES = 4_000_000
LEAST_BUCKETS = 256
#: Text hashed at a time.
SLICE_BYTES = 1_000_000
MIX = np.uint64(0x9E3779B97F4A7C15)


def finish(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(29))


#: White space of one byte, and all other white space of str.split.
SPACES = np.isin(np.arange(256), [*range(9, 14), *range(28, 33)])
WIDE_SPACES = re.compile("[\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")
#: A word is hashed as the sum over its bytes of a number of the byte times one of the place; longer words than this by xxhash.
LONG_WORD = 256
OF_BYTE = np.array([xxhash.xxh64_intdigest(bytes([i])) for i in range(256)], np.uint64)
OF_PLACE = np.multiply.accumulate(np.full(LONG_WORD, xxhash.xxh64_intdigest(b"place") | 1, np.uint64))


def word_hashes(texts: list) -> tuple[np.ndarray, np.ndarray]:
    """(number of words of each text, hashes of all words): lower-cased, separated by white space."""
    numbers, hashes = [np.zeros(0, np.int64)], [np.zeros(0, np.uint64)]
    at = 0
    while at < len(texts):
        raw, size = [], 0
        while at < len(texts) and size < SLICE_BYTES:
            low = (texts[at] or "").lower()
            if not low.isascii():
                low = WIDE_SPACES.sub(" ", low)
            raw.append(low.encode("utf-8", "surrogatepass"))
            size += len(raw[-1]) + 1
            at += 1
        joined = b" ".join(raw)
        data = np.frombuffer(joined, np.uint8)
        inside = np.zeros(len(data) + 2, np.int8)
        inside[1:-1] = ~SPACES[data]
        edge = np.diff(inside)
        start, length = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        length -= start
        begin = np.cumsum([0, *(len(x) + 1 for x in raw)])
        numbers.append(np.diff(np.searchsorted(start, begin)))
        if not len(start):
            continue
        first = np.cumsum(length) - length
        place = np.arange(int(length.sum()))
        place -= np.repeat(first, length)
        np.minimum(place, LONG_WORD - 1, out=place)
        value = OF_BYTE[data[inside[1:-1].view(bool)]]
        value *= OF_PLACE[place]
        made = finish(np.add.reduceat(value, first))
        for i in np.flatnonzero(length > LONG_WORD).tolist():
            made[i] = xxhash.xxh64_intdigest(joined[start[i]:start[i] + length[i]])
        hashes.append(made)
    return np.concatenate(numbers), np.concatenate(hashes)


class Block:
    """Words of some documents side by side."""

    def __init__(self, texts: list):
        self.n_words, self.word = word_hashes(texts)
        self.doc = np.repeat(np.arange(len(texts)), self.n_words)
        self.pos = np.arange(len(self.word)) - np.repeat(np.cumsum(self.n_words) - self.n_words, self.n_words)
        self.levels: dict[int, tuple] = {}
        self.outside: dict[int, np.ndarray] = {}  # occurrences of the n-gram that ends at each position, in other documents

    def level(self, k: int):
        """(positions where an n-gram of k words that may occur elsewhere ends, its distinct hashes sorted, index into them)."""
        if k not in self.levels:
            at = np.flatnonzero(self.pos >= k - 1)
            if k > 2:
                shorter = self.outside[k - 1]
                at = at[(shorter[at] > 0) & (shorter[at - 1] > 0)]
            h = np.full(len(at), np.uint64(k))
            for i in range(k - 1, -1, -1):
                h = h * MIX + self.word[at - i]
            self.levels[k] = (at, *np.unique(finish(h), return_inverse=True))
        return self.levels[k]

    def learn(self, k: int, counts: np.ndarray) -> None:
        """counts: over all blocks, of the distinct hashes of level k."""
        at, _, index = self.level(k)
        _, own, n = np.unique(index * max(1, len(self.n_words)) + self.doc[at], return_inverse=True, return_counts=True)
        out = np.zeros(len(self.word), np.int64)
        out[at] = counts[index] - n[own]
        self.outside[k] = out

    def scores(self, order: int, total: int, alpha: float) -> np.ndarray:
        """Sum of logarithms of each document."""
        n = len(self.word)
        value, back, todo = np.zeros(n), np.zeros(n, np.int64), np.ones(n, bool)
        for k in range(order, 1, -1):
            can = todo & (self.pos >= k - 1)
            hit = np.flatnonzero(can & (self.outside[k] > 0))
            value[hit] = np.log(self.outside[k][hit]) - np.log(self.outside[k - 1][hit - 1])
            can[hit] = False
            todo[hit] = False
            back[can] += 1
        rest = np.flatnonzero(todo)
        seen = self.outside[1][rest]
        others = np.maximum(total - self.n_words, 1)[self.doc[rest]]
        value[rest] = np.log(np.maximum(seen, 1)) - np.log(others)
        back[rest[seen == 0]] += 1
        return np.bincount(self.doc, weights=value + back * np.log(alpha), minlength=len(self.n_words))


def packed(x: np.ndarray) -> bytes:
    """Numbers byte plane by byte plane, compressed: planes that hold little take little."""
    flat = np.ascontiguousarray(x.view(np.uint8).reshape(len(x), -1).T)
    return zstandard.ZstdCompressor(level=1).compress(flat.tobytes())


def unpacked(data: bytes, kind) -> np.ndarray:
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8)
    return np.ascontiguousarray(raw.reshape(np.dtype(kind).itemsize, -1).T).view(kind).ravel()


def packed_keys(keys: np.ndarray) -> bytes:
    """Sorted numbers as steps; those of one bucket lie close."""
    return packed(np.diff(keys, prepend=np.uint64(0)))


def unpacked_keys(data: bytes) -> np.ndarray:
    return np.cumsum(unpacked(data, np.uint64), dtype=np.uint64)


def log2_of(n: int) -> int:
    return max(0, (n - 1).bit_length())


SENT = "block long, bucket long, k int, keys binary, counts binary"


def sender(orders: tuple, bits: int):
    def send(block: int, made: Block):
        out = {n: [] for n in ("block", "bucket", "k", "keys", "counts")}
        for k in orders:
            _, keys, index = made.level(k)
            n = np.bincount(index, minlength=len(keys)).astype(np.uint32)
            of = (keys >> np.uint64(64 - bits)).astype(np.int64)
            cuts = np.concatenate(([0], np.flatnonzero(of[1:] != of[:-1]) + 1, [len(keys)])) if len(keys) else [0]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                for name, v in zip(out, (block, int(of[a]), k, packed_keys(keys[a:b]), packed(n[a:b])), strict=True):
                    out[name].append(v)
        return pa.table([pa.array(v, t) for v, t in zip(out.values(), (pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.binary()), strict=True)], names=list(out))

    return send


def counted(sent: DataFrame) -> DataFrame:
    """block, bucket, k, counts: counts over all blocks of the n-grams that each block sent."""
    def run(table: pa.Table) -> pa.Table:
        keys = [unpacked_keys(x) for x in table.column("keys").to_pylist()]
        own = np.concatenate([unpacked(x, np.uint32) for x in table.column("counts").to_pylist()])
        _, index = np.unique(np.concatenate(keys), return_inverse=True)
        total = np.bincount(index, weights=own).astype(np.int64)[index]  # exact below 2**53
        cuts = np.cumsum([len(x) for x in keys])[:-1]
        back = [packed(x) for x in np.split(total, cuts)]
        return pa.table([table.column("block"), table.column("bucket"), table.column("k"), pa.array(back, pa.binary())], names=["block", "bucket", "k", "counts"])

    return sent.groupBy("bucket", "k").applyInArrow(run, "block long, bucket long, k int, counts binary")


def gathered(docs: DataFrame, blocks: int) -> DataFrame:
    """block, ids, lengths, data: the documents of a batch that belong to one block, as one compressed row."""

    def run(batch: pa.RecordBatch):
        out = {n: [] for n in ("block", "ids", "lengths", "data")}
        of = np.array(common.column_of(batch, "block").to_pylist(), np.int64)
        # Repeated ids (null ones too) are dealt on in turn, so that no block has all of them.
        ids_of, seen = common.column_of(batch, "doc_id").to_pylist(), {}
        for i, one in enumerate(ids_of):
            nth = seen[one] = seen.get(one, -1) + 1
            of[i] = (of[i] + nth) % blocks
        ids, texts = common.column_of(batch, "doc_id").to_pylist(), common.texts_of(batch)
        order = np.argsort(of, kind="stable")
        for part in np.split(order, np.flatnonzero(np.diff(of[order])) + 1):
            raw = [(texts[i] or "").encode("utf-8", "surrogatepass") for i in part.tolist()]
            for name, v in zip(out, (int(of[part[0]]), [ids[i] for i in part.tolist()], packed(np.array([len(x) for x in raw], np.uint32)), zstandard.ZstdCompressor(level=1).compress(b"".join(raw))), strict=True):
                out[name].append(v)
        return out

    placed = docs.select(F.pmod(F.xxhash64("doc_id"), F.lit(blocks)).alias("block"), "doc_id", "text")
    return common.arrow_map(placed, run, "block long, ids array<long>, lengths binary, data binary")


def block_of(docs: pa.Table) -> tuple[list, Block]:
    """(ids, words) of the documents of a block."""
    ids, texts = [], []
    for own, lengths, data in zip(docs.column("ids").to_pylist(), docs.column("lengths").to_pylist(), docs.column("data").to_pylist(), strict=True):
        ids += own
        raw = zstandard.ZstdDecompressor().decompress(data)
        stops = np.cumsum(unpacked(lengths, np.uint32), dtype=np.int64).tolist()
        texts += [raw[a:b].decode("utf-8", "surrogatepass") for a, b in zip([0, *stops[:-1]], stops, strict=True)]
    return ids, Block(texts)


def taught(made: Block, counts: pa.Table, order: int) -> Block:
    rows = sorted(zip(counts.column("k").to_pylist(), counts.column("bucket").to_pylist(), counts.column("counts").to_pylist(), strict=True), key=lambda r: r[:2])
    for k in range(1, order + 1):
        made.learn(k, np.concatenate([np.zeros(0, np.int64), *(unpacked(r[2], np.int64) for r in rows if r[0] == k)]))
    return made


def resender(send, order: int):
    def phase(docs: pa.Table, counts: pa.Table) -> pa.Table:
        return send(docs.column("block")[0].as_py(), taught(block_of(docs)[1], counts, order))

    return phase


def corpus_size(docs: DataFrame) -> tuple[int, int]:
    """(bytes of text, words)."""

    def run(batch: pa.RecordBatch):
        texts = [t or "" for t in common.texts_of(batch)]
        return {"size": [sum(len(t.encode("utf-8", "surrogatepass")) for t in texts)], "words": [sum(len(t.split()) for t in texts)]}

    r = common.arrow_map(docs.select("text"), run, "size long, words long").agg(F.sum("size"), F.sum("words")).first()
    return r[0] or 0, r[1] or 0


def stupid_backoff(docs: DataFrame, *, order: int = ORDER, alpha: float = ALPHA, block_bytes: int = BLOCK_BYTES, bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    if order < 2:
        raise ValueError("order must be 2 or more")
    size, total = corpus_size(docs)
    blocks = max(1, -(-size // block_bytes))
    bits = log2_of(max(LEAST_BUCKETS, -(-size // bucket_bytes)))
    by_block = gathered(docs, blocks).groupBy("block")  # the same exchange serves every phase
    first = sender((1, 2), bits)

    def phase_one(table: pa.Table) -> pa.Table:
        return first(table.column("block")[0].as_py(), block_of(table)[1])

    known = counted(by_block.applyInArrow(phase_one, SENT))
    for k in range(3, order + 1):
        longer = resender(sender((k,), bits), k - 1)
        known = known.unionByName(counted(by_block.cogroup(known.groupBy("block")).applyInArrow(longer, SENT)))

    def score(docs: pa.Table, counts: pa.Table) -> pa.Table:
        ids, made = block_of(docs)
        taught(made, counts, order)
        sums = made.scores(order, total, alpha)
        n = made.n_words
        mean = [round(float(s) / int(c), 6) if c else None for s, c in zip(sums, n, strict=True)]
        return pa.table([pa.array(ids, pa.int64()), pa.array(n, pa.int64()), pa.array(mean, pa.float64())], names=["doc_id", "n_words", "mean_log"])

    return by_block.cogroup(known.groupBy("block")).applyInArrow(score, "doc_id long, n_words long, mean_log double")


def op9_stupid_backoff(spark, sf_dir):
    return stupid_backoff(common.documents(spark, sf_dir))
