"""Best-fit packing with swap-based local search.

Documents become pieces of at most ``capacity`` tokens; pieces go into as few sequences as can be. A
piece of full length is a sequence. The others are dealt at random (by hash) into groups of
about GROUP_PIECES pieces, which are packed apart from each other: first by best fit, longest first; then by a
local search between underfull bins that exchanges one piece for one, two for one, or moves a
piece, whenever that raises the sum of squared fills. Each such step makes full bins fuller
and poor bins poorer until poor ones are empty and vanish. A group loses at most part of one bin against
packing everything at once, so the loss shrinks as 1 / GROUP_PIECES and does not grow with the input.

Defined results: null text is empty and still has its end token; repeated rows are packed
each (their stored row number keeps them apart); an empty table gives an empty table; other columns are ignored.
"""

import bisect
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, tokens

CAPACITY = 4096
END_ID = 1
#: Pieces of a group on average: memory of a task and quality of packing.
GROUP_PIECES = 8_000
#: Rounds of the local search; it ends sooner when a round changes nothing.
ROUNDS = 6


def pieces(docs: DataFrame, vocabulary: str, *, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every piece of every document."""
    end = int(end_id).to_bytes(4, "little")

    def run(batch: pa.RecordBatch):
        ids, counts = tokens.encoder(vocabulary, fold=True)(common.column_of(batch, "text"))
        data, sizes = memoryview(ids.tobytes()), (4 * counts).tolist()
        out = {k: [] for k in ("doc_id", "piece", "start", "length", "ids_crc32")}
        place = 0
        for doc, size in zip(common.column_of(batch, "doc_id").to_pylist(), sizes, strict=True):
            for k, at in enumerate(range(0, size + 4, 4 * capacity)):
                stop = min(at + 4 * capacity, size + 4)
                crc = zlib.crc32(data[place + at:place + min(stop, size)])
                if stop > size:
                    crc = zlib.crc32(end, crc)
                for name, v in zip(out, (doc, k, at // 4, (stop - at) // 4, crc), strict=True):
                    out[name].append(v)
            place += size
        return out

    return common.arrow_map(docs.select("doc_id", "text"), run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def best_fit(lengths: np.ndarray, capacity: int) -> list[list[int]]:
    """Bins of indexes: longest first, each into the fullest bin that has room. Bins are kept by their room."""
    by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    rooms: list[int] = []  # rooms that some bin has, sorted
    bins: list[list[int]] = []
    for i in np.argsort(-lengths, kind="stable"):
        n = int(lengths[i])
        at = bisect.bisect_left(rooms, n)
        if at < len(rooms):
            room = rooms[at]
            b = by_room[room].pop()
            if not by_room[room]:
                rooms.pop(at)
        else:
            room, b = capacity, len(bins)
            bins.append([])
        bins[b].append(int(i))
        left = room - n
        if not by_room[left]:
            bisect.insort(rooms, left)
        by_room[left].append(b)
    return bins


def local_search(lengths: np.ndarray, bins: list[list[int]], capacity: int, rounds: int = ROUNDS) -> list[list[int]]:
    """Raise the sum of squared fills by moves and exchanges between underfull bins; drop bins that empty.

    Every underfull bin gives in turn, the least full first; all others take, the fullest first. A giver's piece moves into a
    bin with room for it; or it is exchanged for one smaller piece, or for two smaller pieces, of that bin, so that the
    bin gains at most its room. A step is taken if and only if it raises the sum of squares, that is if the taker ends fuller than the giver was;
    so the search ends. It ends sooner when the bins are as few as the total allows.
    """
    size = lengths.tolist()
    bins = [list(b) for b in bins if b]
    fill = [sum(size[i] for i in b) for b in bins]
    least = -(-sum(fill) // capacity)
    live = len(bins)
    for _ in range(rounds):
        if live <= least:
            break
        takers = sorted((b for b in range(len(bins)) if bins[b] and fill[b] < capacity), key=lambda b: (fill[b], b))
        changed = False
        for donor in takers:
            if live <= least:
                break
            others = sorted((b for b in takers if b != donor and bins[b]), key=lambda b: (capacity - fill[b], b))
            for i in sorted(bins[donor], key=lambda i: -size[i]):
                n = size[i]
                for b in others:
                    if fill[b] + n <= fill[donor] or fill[b] == capacity:
                        continue  # no exchange can end above the giver's fill
                    give = exchange(size, bins[b], n, capacity - fill[b])
                    if give is None:
                        continue
                    gain = n - sum(size[j] for j in give)
                    if fill[b] + gain <= fill[donor]:
                        continue
                    bins[donor].remove(i)
                    bins[b] = [j for j in bins[b] if j not in give] + [i]
                    bins[donor] += give
                    fill[b] += gain
                    fill[donor] -= gain
                    changed = True
                    break
            live -= not bins[donor]
        if not changed:
            break
    return [b for b in bins if b]


def exchange(size: list[int], items: list[int], n: int, room: int) -> list[int] | None:
    """What a bin gives for a piece of n tokens: nothing if it fits, else one or two pieces of n - room to n - 1 tokens in all, as few tokens as can be.

    Pieces of one size stand for each other, two of them at most; different sizes in a bin are few, as their sum is bounded by the capacity.
    """
    if n <= room:
        return []
    low = n - room
    best, cost = None, n
    by_size: dict[int, list[int]] = {}
    for j in items:
        if size[j] < n:
            same = by_size.setdefault(size[j], [])
            if len(same) < 2:
                same.append(j)
            if low <= size[j] < cost:
                best, cost = [j], size[j]
    if cost > low:
        some = sorted((s, j) for s, same in by_size.items() if s < cost for j in same)
        for k, (a, j) in enumerate(some):
            at = bisect.bisect_left(some, (low - a, -1), k + 1)
            if at < len(some) and low <= a + some[at][0] < cost:
                best, cost = [j, some[at][1]], a + some[at][0]
    return best


def pack(made: DataFrame, *, capacity: int = CAPACITY, group_pieces: int = GROUP_PIECES, rounds: int = ROUNDS) -> DataFrame:
    """Pieces with sequence_id (long) and offset (long): place each piece in a sequence, gapless from 0."""
    made = common.stored(made, "pieces")  # tokenize once: the number of groups needs the number of pieces
    groups = max(1, -(-made.count() // group_pieces))
    # The stored files fix the row numbers, so a rerun deals alike, and repeated rows are spread.
    made = made.withColumn("grp", F.pmod(F.xxhash64(F.monotonically_increasing_id(), F.lit("group")), F.lit(groups)))

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["doc_id", "piece", "start", "length", "ids_crc32"], kind="stable", ignore_index=True)
        lengths = pdf["length"].to_numpy()
        full = np.flatnonzero(lengths == capacity)
        part = np.flatnonzero(lengths < capacity)
        bins = local_search(lengths[part], best_fit(lengths[part], capacity), capacity, rounds)
        at, offset = np.empty(len(pdf), np.int64), np.zeros(len(pdf), np.int64)
        at[full] = np.arange(len(full))
        for k, b in enumerate(bins):
            own = part[np.sort(b)]
            at[own] = len(full) + k
            offset[own] = np.cumsum(lengths[own]) - lengths[own]
        pdf["sequence_id"] = int(pdf["grp"].iloc[0]) * 2**32 + at if len(pdf) else at
        pdf["offset"] = offset
        return pdf.drop(columns="grp")

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
    return made.groupBy("grp").applyInPandas(one, schema)


def pack_documents(docs: DataFrame, vocabulary: str, **options) -> DataFrame:
    capacity, end_id = options.pop("capacity", CAPACITY), options.pop("end_id", END_ID)
    return pack(pieces(docs, vocabulary, capacity=capacity, end_id=end_id), capacity=capacity, **options)


def op5_best_fit_packing(spark, sf_dir):
    return pack_documents(common.documents(spark, sf_dir), tokens.vocabulary("word_bpe_49k.json"))
