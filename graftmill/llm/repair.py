"""Token ids in shards compressed by a Re-Pair grammar, decodable from any document on.

Shards hold whole documents in ascending doc_id order. Within a shard the most frequent adjacent pairs are
replaced by new symbols, round after round: a round counts the pairs exactly, takes those that are frequent enough, and replaces
their occurrences at once where they do not overlap (an occurrence gives way to a more frequent neighbour and is met
again in the next round; of a run of one symbol every second pair goes). The bar falls by an eighth with each round, down to LEAST; from
there rounds go on until no pair occurs LEAST times. No rule reaches across the end of a document, so a document is a run of symbols.

File format of a shard (little-endian), one binary value in a Parquet column ``shard``, beside columns for the
place of the shard in the order:

    magic 4 bytes, then six unsigned 32-bit numbers: documents, symbols in the sequence, rules, base (first
    nonterminal), ids, bits of a symbol
    documents x (signed 64-bit doc_id), documents x (unsigned 32-bit first symbol), documents x (unsigned 32-bit ids)
    rules x (unsigned 32-bit left, right), rules x (unsigned 32-bit expansion length)
    the sequence: low 16 bits of each symbol, then one bit plane for each further bit

Defined results: null text is empty and holds only the end id; a null doc_id sorts first and is
written as the smallest number; repeated rows are stored each; an empty table gives no shard and no row; other
columns are ignored.
"""

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common, tokens

# Fixed values of the format.
MAGIC = b"RPG1"
HEADER = "<4s6I"
NULL_ID = -(2**63)
#: Ids of a shard: unit of decoding and bound on a task's memory.
SHARD_IDS = 1 << 20
#: A pair must occur this often in its shard to become a rule.
LEAST = 8
#: Chunks kept by a worker, about 160 bytes each: on check_l they save half of the misses that tokens.CACHE_CHUNKS leaves, and nothing else runs beside this operator.
KEPT_CHUNKS = 800_000
RARE = np.iinfo(np.int32).max


def counted_pairs(seq: np.ndarray, at: np.ndarray, top: int):
    """(places in the order of their pairs, first place of each distinct pair in that order, occurrences of each) of the pairs at ``at``."""
    bits, place = top.bit_length(), len(seq).bit_length()
    if 2 * bits + place <= 64:  # pair and place in one number: sorted at once
        key = seq[at].astype(np.uint64)
        key <<= np.uint64(bits)
        key |= seq[at + 1]
        key <<= np.uint64(place)
        key |= at.astype(np.uint64)
        key.sort()
        where = (key & np.uint64((1 << place) - 1)).astype(np.int64)
        key >>= np.uint64(place)
    else:
        key = (seq[at].astype(np.uint64) << np.uint64(32)) | seq[at + 1]
        by = np.argsort(key, kind="stable")
        where, key = at[by], key[by]
    first = np.concatenate(([0], np.flatnonzero(key[1:] != key[:-1]) + 1))
    return where, first, np.diff(np.append(first, len(key)))


def compress(ids: np.ndarray, lengths: np.ndarray, *, least: int = LEAST):
    """(sequence, first symbol of each document, rules[n, 2], base) for documents of the given lengths, end ids included.

    A pair's count only falls once its symbols exist. So each place keeps the last count of its pair as a bound, and is not looked at again
    until the bar has fallen to it or one of its two symbols is replaced.
    """
    seq = ids.astype(np.uint32)
    base = int(seq.max()) + 1 if len(seq) else 0
    ends = np.cumsum(lengths) - 1
    most = np.full(len(seq), RARE, np.int32)  # RARE: not counted yet; 0: no pair starts here; -1: the end id of a document, in no pair
    most[ends[ends > 0] - 1] = 0
    most[ends] = -1
    rules = [np.zeros((0, 2), np.uint32)]
    made, r = 0, 0
    while len(seq) >= 2:
        bar = max(least, len(seq) >> (6 + 3 * r))  # an eighth of the one before
        r += 1
        at = np.flatnonzero(most >= bar)
        if not len(at):
            if bar == least:
                break
            continue
        where, first, counts = counted_pairs(seq, at, base + made)
        most[where] = np.repeat(counts, counts)
        good = np.flatnonzero(counts >= bar)
        if not len(good):
            if bar == least:
                break
            continue
        good = good[np.argsort(-counts[good], kind="stable")]
        size = counts[good]
        spots = where[np.repeat(first[good] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))]
        rank = np.full(len(seq) + 1, RARE, np.int32)  # the last one stands before the first, too
        rank[spots] = np.repeat(np.arange(len(good), dtype=np.int32), size)
        own = rank[spots]
        best = np.zeros(len(seq), bool)
        best[spots[(own <= rank[spots - 1]) & (own <= rank[spots + 1])]] = True
        spots = np.flatnonzero(best)  # neighbours among them are pairs of one symbol
        fresh = np.concatenate(([True], spots[1:] > spots[:-1] + 1))
        nth = np.arange(len(spots))
        take = spots[(nth - nth[fresh][np.cumsum(fresh) - 1]) % 2 == 0]
        used = np.zeros(len(good), bool)
        used[rank[take]] = True
        number = np.cumsum(used) - 1
        heads = where[first[good[used]]]
        rules.append(np.stack((seq[heads], seq[heads + 1]), axis=1))
        seq[take] = base + made + number[rank[take]]
        made += len(heads)
        # The new symbol pairs with its neighbours, unless a document ends there.
        most[take] = np.where(most[take + 2] < 0, 0, RARE)
        before = take[take > 0] - 1
        most[before[most[before] >= 0]] = RARE
        keep = np.ones(len(seq), bool)
        keep[take + 1] = False
        seq, most = seq[keep], most[keep]
    first = np.concatenate(([0], np.flatnonzero(most < 0)[:-1] + 1)) if len(lengths) else np.zeros(0, np.int64)
    return seq, first, np.concatenate(rules), base


def expansion_lengths(rules: np.ndarray, base: int) -> np.ndarray:
    out = np.ones(len(rules), np.int64)
    done = 0
    while done < len(rules):  # rules of a round refer to earlier rounds only
        later = np.flatnonzero((rules[done:] >= base + done).any(axis=1))
        end = done + int(later[0]) if len(later) else len(rules)
        part = rules[done:end].astype(np.int64)
        size = np.ones(part.shape, np.int64)
        old = part >= base
        size[old] = out[part[old] - base]
        out[done:end] = size.sum(axis=1)
        done = end
    return out


def expand(seq: np.ndarray, rules: np.ndarray, base: int) -> np.ndarray:
    """Ids of a run of symbols."""
    seq = np.asarray(seq, np.uint32)
    while True:
        big = seq >= base
        if not big.any():
            return seq
        at = np.cumsum(np.where(big, 2, 1)) - np.where(big, 2, 1)
        out = np.empty(int(at[-1]) + (2 if big[-1] else 1), np.uint32)
        out[at[~big]] = seq[~big]
        pair = rules[seq[big] - base]
        out[at[big]] = pair[:, 0]
        out[at[big] + 1] = pair[:, 1]
        seq = out


def write_shard(doc_ids: list, ids: np.ndarray, lengths: np.ndarray) -> bytes:
    seq, first, rules, base = compress(ids, lengths)
    top = base + len(rules)
    bits = max(16, top.bit_length())
    planes = b"".join(np.packbits((seq >> b) & 1).tobytes() for b in range(16, bits))
    keys = np.array([NULL_ID if d is None else d for d in doc_ids], np.int64)
    return b"".join((struct.pack(HEADER, MAGIC, len(keys), len(seq), len(rules), base, len(ids), bits), keys.tobytes(), first.astype(np.uint32).tobytes(), lengths.astype(np.uint32).tobytes(), rules.tobytes(), expansion_lengths(rules, base).astype(np.uint32).tobytes(), (seq & 0xFFFF).astype(np.uint16).tobytes(), planes))


class Shard:
    """Reads a shard; any document decodes alone."""

    def __init__(self, data: bytes):
        magic, docs, symbols, rules, self.base, self.n_ids, bits = struct.unpack_from(HEADER, data)
        if magic != MAGIC:
            raise ValueError("not a grammar shard")
        at = struct.calcsize(HEADER)

        def take(kind, n):
            nonlocal at
            out = np.frombuffer(data, kind, n, at)
            at += out.nbytes
            return out

        self.doc_ids = [None if d == NULL_ID else d for d in take("<i8", docs).tolist()]
        self.first, self.lengths = take("<u4", docs), take("<u4", docs)
        self.rules = take("<u4", 2 * rules).reshape(-1, 2)
        self.expansions = take("<u4", rules)
        self.seq = take("<u2", symbols).astype(np.uint32)
        for b in range(16, bits):
            plane = np.unpackbits(take("u1", -(-symbols // 8)), count=symbols)
            self.seq |= plane.astype(np.uint32) << np.uint32(b)

        # All expansions one after another: a run of symbols is then read with one gather.
        size = np.concatenate((np.ones(self.base, np.int64), self.expansions))
        self.size, self.place = size, np.cumsum(size) - size
        tops = np.arange(self.base, self.base + rules, dtype=np.uint32)
        self.flat = np.concatenate((np.arange(self.base, dtype=np.uint32), expand(tops, self.rules, self.base)))

    def read(self, run: np.ndarray) -> np.ndarray:
        size = self.size[run]
        return self.flat[np.repeat(self.place[run] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))]

    def document(self, i: int) -> np.ndarray:
        end = self.first[i + 1] if i + 1 < len(self.first) else len(self.seq)
        return self.read(self.seq[self.first[i]:end])

    def ids_at(self, i: int, start: int, stop: int) -> np.ndarray:
        """Ids start..stop of a document: only the symbols that reach into the range are expanded."""
        end = self.first[i + 1] if i + 1 < len(self.first) else len(self.seq)
        run = self.seq[self.first[i]:end]
        stops = np.cumsum(self.size[run])
        lo, hi = np.searchsorted(stops, start, side="right"), np.searchsorted(stops, stop, side="left") + 1
        before = int(stops[lo - 1]) if lo else 0
        return self.read(run[lo:hi])[start - before:stop - before] if lo < len(run) else run[:0]

    def all_ids(self) -> np.ndarray:
        return self.read(self.seq)


def write_ids(docs: DataFrame, vocabulary: str, path: str, *, end_id: int = 2, shard_ids: int = SHARD_IDS) -> None:
    """Encode, sort by doc_id and write the shards below ``path``: columns part, shard_no, first_doc, n_docs, n_ids, shard."""
    ordered = docs.select("doc_id", "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    schema = "part long, shard_no long, first_doc long, n_docs long, n_ids long, shard binary"

    def run(batches):
        encode = tokens.encoder(vocabulary, fold=False, most=KEPT_CHUNKS)
        part, number = TaskContext.get().partitionId(), 0
        keys, data, lengths, size = [], [], [], 0

        def made():
            row = [part, number, keys[0], len(keys), size, write_shard(keys, np.concatenate(data), np.array(lengths, np.int64))]
            return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, [pa.int64()] * 5 + [pa.binary()], strict=True)], names=[f.split()[0] for f in schema.split(", ")])

        for batch in batches:
            ids, counts = encode(common.column_of(batch, "text"))
            counts += 1
            ends = np.cumsum(counts)
            whole = np.full(int(ends[-1]) if len(ends) else 0, end_id, np.uint32)
            inner = np.ones(len(whole), bool)
            inner[ends - 1] = False
            whole[inner] = ids
            for doc, n, stop in zip(common.column_of(batch, "doc_id").to_pylist(), counts.tolist(), ends.tolist(), strict=True):
                if keys and size + n > shard_ids:
                    yield made()
                    number += 1
                    keys, data, lengths, size = [], [], [], 0
                keys.append(doc)
                data.append(whole[stop - n:stop])
                lengths.append(n)
                size += n
        if keys:
            yield made()
        common.tidy()

    ordered.mapInArrow(run, schema).write.parquet(path)


def read_ids(spark, path: str, *, with_ids: bool = True) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 and (with_ids) ids (binary, little-endian unsigned 32-bit) of every document, from the files."""
    files = spark.read.schema("part long, shard_no long, first_doc long, n_docs long, n_ids long, shard binary").parquet(path)
    # One number for each written partition reaches the driver; the order within a partition is a window of its few shards.
    sums = sorted((r["part"], r["n"]) for r in files.groupBy("part").agg(F.sum("n_ids").alias("n")).collect())
    starts, total = [], 0
    for part, n in sums:
        starts.append((part, total))
        total += n
    before = spark.createDataFrame(starts, "part long, part_start long")
    w = Window.partitionBy("part").orderBy("shard_no").rowsBetween(Window.unboundedPreceding, -1)
    places = files.select("part", "shard_no", "n_ids").withColumn("__own", F.coalesce(F.sum("n_ids").over(w), F.lit(0)))
    places = places.join(F.broadcast(before), "part").select("part", "shard_no", (F.col("part_start") + F.col("__own")).alias("shard_start"))

    def decode(batch: pa.RecordBatch):
        out = []
        for data, at in zip(common.column_of(batch, "shard"), common.column_of(batch, "shard_start").to_pylist(), strict=True):
            shard = Shard(data.as_py())
            ids = shard.all_ids().tobytes()
            ends = np.cumsum(shard.lengths.astype(np.int64))
            begin = ends - shard.lengths
            parts = [ids[4 * a:4 * b] for a, b in zip(begin.tolist(), ends.tolist(), strict=True)]
            out.append({"doc_id": shard.doc_ids, "start": at + begin, "n_tokens": shard.lengths.astype(np.int64), "ids_crc32": [zlib.crc32(x) for x in parts]} | ({"ids": parts} if with_ids else {}))
        return out

    schema = "doc_id long, start long, n_tokens long, ids_crc32 long" + (", ids binary" if with_ids else "")

    return common.arrow_map(files.join(places, ["part", "shard_no"]).select("shard", "shard_start"), decode, schema)


def op7_repair_ids(spark, sf_dir):
    path = common.shared_folder(spark, "ids")
    write_ids(common.documents(spark, sf_dir), tokens.vocabulary("byte_bpe_50k.json"), path)
    return read_ids(spark, path, with_ids=False)
