"""Removal of repeated byte strings with merged Burrows-Wheeler transforms.

Every byte covered by a string of ``length`` bytes that starts anywhere else too is removed. The work
is cut down exactly, step by step:

1. Anchors. Every window of ``length`` bytes has one anchor: the gram of GRAM bytes in it with the least hash
   (the last such gram). Equal windows have equal anchors at the same place. Windows that follow each other and share
   their anchor form a context: the bytes from the first window's start to the last one's end.
2. Anchors are counted, eight bytes each. Contexts of an anchor that occurs once are unique and go.
3. The contexts of repeated anchors are listed with a 128-bit BLAKE2 digest of their bytes, without the bytes. Contexts with equal
   digests are equal: all of their windows repeat.
4. Of each distinct context of an anchor with several, one copy's bytes go to the tasks of its anchor. There, contexts
   are strings over 16-byte symbols, aligned to the anchor. Shards of them get a suffix order and a Burrows-Wheeler transform
   each; the transforms are merged by interleave refinement, whose passes yield the common prefixes. Intervals of rows
   with a common prefix of (length / 16 - 1) symbols are repeated at symbol level.
5. An exact comparison of the up to 15 bytes at either end settles the windows within such an interval.
6. The ranges return to their documents by one join, to which only documents with ranges are sent.

Each of the steps 2 to 4 and 6 is a pass over the texts where they lie: no text is exchanged but those of step 6. What a pass looks for is a fixed-size
sketch (FILTER_BITS bits, one for each hash). A sketch only lets too much through, never too little; what it lets through is
decided exactly afterwards (counts by anchor, equality of digests, the join), or does no harm: in step 4 another copy of a context
or a context of a unique anchor adds no window that does not repeat. So a full sketch costs time, not results.

An anchor with more than GROUP distinct contexts is dealt in blocks, one task for each pair of blocks; the contexts of a digest or an anchor with
very many meet its count in a broadcast of bounded size. So no task grows with a hot passage and none of it is dropped.

By words. drop_repeats(words=n) removes every run of n words that starts anywhere else too, however few bytes it has. Each word
becomes a code of WORD bytes (a hash of its characters without punctuation at either end) and the steps above run on the
codes with a length of n codes; of the ranges found, those that hold n whole codes count. A character of a script
without spaces is a word. Words are told apart by 48 bits, a run by all of its words.

Defined results: null text is empty; a text shorter than ``length`` keeps all its bytes; repeated rows (same doc_id and text)
repeat each other and so lose all from ``length`` bytes on; an empty table gives an empty table; other columns are ignored.
"""

import hashlib
import unicodedata

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bwt, common

LENGTH = 400
GRAM = 32
SYMBOL = 16
#: Distinct contexts of one anchor on one side of a task.
GROUP = 8192
#: Contexts merged at a time, and of one shard.
CHUNK, SHARD = 8192, 2048
#: Texts whose contexts are held at a time.
ROWS = 256
#: Window starts taken at a time in a very long text.
SLICE = 1 << 19
BITS = 20
#: Bits of a sketch: 16 MB on the driver, in the broadcast and in each worker, whatever the input.
FILTER_BITS = 27
#: Anchors with more than GROUP contexts that are broadcast; beyond this number they are joined.
HOT_ANCHORS = 100_000
#: Bytes of a word's code.
WORD = 6
#: Scripts written without spaces: Thai and Lao, Tibetan, Myanmar, Khmer, kana, Han.
UNSPACED = ((0xE00, 0xEFF), (0xF00, 0xFFF), (0x1000, 0x109F), (0x1780, 0x17FF), (0x3005, 0x3007), (0x3040, 0x30FF), (0x3400, 0x9FFF), (0xF900, 0xFAFF), (0x20000, 0x3FFFF))
SPACE, LETTER, MARK, LONE = range(4)

# Odd multipliers, fixed.
M1, M2 = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F  # of grams, of places


def finish(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(29))


def powers(n: int):
    """m**i and m**-i modulo 2**64, i < n."""
    cache = common.process_cache("powers")
    if len(cache.get("p", [[]])[0]) < n:
        size = 1 << max(18, (n - 1).bit_length())
        out = []
        for base in (M1, pow(M1, -1, 2**64)):
            p = np.full(size, np.uint64(base))
            p[0] = 1
            out.append(np.multiply.accumulate(p))
        cache["p"] = out
    return [p[:n] for p in cache["p"]]


def contexts(data: bytes, length: int, gram: int):
    """Arrays (anchor hash, start, windows, anchor place) of the contexts of one text."""
    n = len(data)
    b = np.frombuffer(data, np.uint8).astype(np.uint64) + np.uint64(1)
    p1, q1 = powers(n + 1)
    s1 = np.concatenate((np.zeros(1, np.uint64), np.cumsum(b * p1[:n], dtype=np.uint64)))
    h = finish((s1[gram:] - s1[:-gram]) * q1[:n - gram + 1])
    w = length - gram + 1
    anchors, starts = [], []
    for lo in range(0, n - length + 1, SLICE):
        k = h[lo:lo + SLICE + w - 1]
        m = len(k) - w + 1
        key = (k >> np.uint64(BITS) << np.uint64(BITS)) | np.arange((1 << BITS) - 1, (1 << BITS) - 1 - len(k), -1, dtype=np.int64).astype(np.uint64)
        grid = np.full(-(-len(k) // w) * w, np.uint64(2**64 - 1))
        grid[:len(k)] = key
        grid = grid.reshape(-1, w)
        left = np.minimum.accumulate(grid, axis=1).ravel()
        right = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
        least = np.minimum(right[:m], left[w - 1:w - 1 + m])
        at = ((1 << BITS) - 1) - (least & np.uint64((1 << BITS) - 1)).astype(np.int64)
        new = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
        anchors.append(at[new] + lo)
        starts.append(new + lo)
    anchor, start = np.concatenate(anchors), np.concatenate(starts)
    windows = np.diff(np.concatenate((start, [n - length + 1])))
    return h[anchor], start, windows, anchor - start


def classes() -> np.ndarray:
    """SPACE, LETTER, MARK (punctuation) or LONE (a word of its own) for every code point."""
    cache = common.process_cache("classes")
    if not cache:
        kind = np.full(0x110000, LETTER, np.uint8)
        for i in range(0x10000):
            c = chr(i)
            kind[i] = SPACE if c.isspace() else LETTER if c.isalnum() or unicodedata.category(c)[0] == "M" else MARK
        for lo, hi in UNSPACED:
            kind[lo:hi + 1][kind[lo:hi + 1] == LETTER] = LONE
        cache["kind"] = kind
    return cache["kind"]


def word_spans(text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first character, end, kind of every character) of the words."""
    points = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    kind = classes()[points]
    solid = kind != SPACE
    new = solid.copy()
    new[1:] &= ~solid[:-1] | (kind[1:] == LONE) | (kind[:-1] == LONE) & (kind[1:] != MARK)
    start = np.flatnonzero(new)
    if not len(start):
        return start, start, kind
    last = np.flatnonzero(solid)
    return start, last[np.searchsorted(last, np.append(start[1:], len(text))) - 1] + 1, kind


def word_codes(data: bytes) -> bytes:
    """WORD bytes for each word of a text."""
    text = data.decode()
    start, end, kind = word_spans(text)
    if not len(start):
        return b""
    good = np.flatnonzero((kind == LETTER) | (kind == LONE))
    a, b = np.searchsorted(good, start), np.searchsorted(good, end)
    some = b > a  # others are punctuation only and count as they are
    start, end = start.copy(), end.copy()
    start[some], end[some] = good[a[some]], good[b[some] - 1] + 1
    p, q = powers(len(text) + 1)
    sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum((np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.uint64) + np.uint64(1)) * p[:len(text)], dtype=np.uint64)))
    h = finish((sums[end] - sums[start]) * q[start])
    return h.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :WORD].tobytes()


def each_context(docs: DataFrame, made, schema: str, length: int, gram: int, by_word: bool) -> DataFrame:
    """Rows that made(doc_id, key, bytes, contexts of them) gives (a dict of columns, or None) for each text that has a window."""

    def run(batch: pa.RecordBatch):
        out = []
        for doc, key, data in zip(*(common.column_of(batch, c).to_pylist() for c in ("doc_id", "key", "data")), strict=True):
            if by_word and data is not None:
                data = word_codes(data)
            if data is not None and len(data) >= length:
                one = made(doc, key, data, contexts(data, length, gram))
                if one is not None:
                    out.append(one)
        if not out:
            return None
        return {n: np.concatenate([x[n] for x in out]) if isinstance(out[0][n], np.ndarray) else [v for x in out for v in x[n]] for n in out[0]}

    return common.arrow_map(docs, run, schema, ROWS)


def sketch(hashes: DataFrame):
    """A broadcast of the bits of a column of 64-bit hashes: bit (hash mod 2**FILTER_BITS) is set for each."""
    bit = F.col(hashes.columns[0]).bitwiseAND(F.lit((1 << FILTER_BITS) - 1))
    words = hashes.select(F.shiftright(bit, 6).cast("int").alias("word"), F.expr(f"shiftleft(1L, cast(`{hashes.columns[0]}` & 63 as int))").alias("bits")).groupBy("word").agg(F.bit_or("bits").alias("bits"))
    table = words.toArrow()  # at most 2**FILTER_BITS / 64 rows
    out = np.zeros(1 << (FILTER_BITS - 6), np.uint64)
    out[table["word"].to_numpy()] = table["bits"].to_numpy().view(np.uint64)
    return hashes.sparkSession.sparkContext.broadcast(out)


def passes(shared, hashes: np.ndarray) -> np.ndarray:
    """Which hashes the sketch lets through."""
    at = hashes.view(np.uint64) & np.uint64((1 << FILTER_BITS) - 1)
    return (shared.value[(at >> np.uint64(6)).astype(np.int64)] >> (at & np.uint64(63))) & np.uint64(1) != 0


def place_hash(fp: np.ndarray, key, start: np.ndarray) -> np.ndarray:
    """One number for a context of a row."""
    return finish(fp ^ finish(np.asarray(key, np.int64).view(np.uint64) + start.astype(np.uint64) * np.uint64(M2)))


def listed_contexts(docs: DataFrame, anchors, length: int, gram: int, by_word: bool) -> DataFrame:
    """The contexts whose anchor the sketch lets through, without their bytes."""

    def made(doc, key, data, found):
        fp, start, windows, place = (x[passes(anchors, found[0])] for x in found)
        if not len(fp):
            return None
        ends = (start + windows - 1 + length).tolist()
        digests = [hashlib.blake2b(data[a:b], digest_size=16, salt=p.to_bytes(4, "little")).digest() for a, b, p in zip(start.tolist(), ends, place.tolist(), strict=True)]
        return {"fp": fp.view(np.int64), "digest": digests, "u": place_hash(fp, key, start).view(np.int64), "doc_id": [doc] * len(fp), "key": [key] * len(fp), "s": start, "e": start + windows - 1 + length}

    return each_context(docs, made, "fp long, digest binary, u long, doc_id long, key long, s long, e long", length, gram, by_word)


def sent_contexts(docs: DataFrame, wanted, length: int, gram: int, by_word: bool) -> DataFrame:
    """The contexts whose place hash the sketch lets through, with their bytes."""

    def made(doc, key, data, found):
        u = place_hash(found[0], key, found[1])
        some = passes(wanted, u)
        fp, start, windows, place = (x[some] for x in found)
        if not len(fp):
            return None
        ends = (start + windows - 1 + length).tolist()
        return {"fp": fp.view(np.int64), "u": u[some].view(np.int64), "doc_id": [doc] * len(fp), "key": [key] * len(fp), "start": start, "windows": windows, "place": place, "data": [data[a:b] for a, b in zip(start.tolist(), ends, strict=True)]}

    return each_context(docs, made, "fp long, u long, doc_id long, key long, start long, windows int, place int, data binary", length, gram, by_word)


def repeated_windows(bufs: list[bytes], windows: list[int], places: list[int], length: int) -> tuple[np.ndarray, np.ndarray]:
    """(context, window) of every window whose bytes are also those of another one, for contexts that share anchors."""
    depth = length // SYMBOL - 1
    ends = length - depth * SYMBOL  # bytes beyond the symbols
    place = np.array(places)
    lead = place % SYMBOL
    size = np.array([len(x) for x in bufs])
    count = (size - lead) // SYMBOL
    pad = b"\0" * SYMBOL
    data = np.frombuffer(pad + b"".join(bufs) + pad + pad, np.uint8)
    at = np.cumsum(size) - size + SYMBOL  # of each context in data
    first = np.cumsum(count + 1) - (count + 1)
    total = int((count + 1).sum())
    owner = np.repeat(np.arange(len(bufs)), count + 1)
    nth = np.arange(total) - first[owner]
    real = nth < count[owner]
    where = at[owner[real]] + lead[owner[real]] + SYMBOL * nth[real]
    pairs = np.lib.stride_tricks.sliding_window_view(data, SYMBOL)[where].copy().view(np.uint64)
    by = np.lexsort((pairs[:, 1], pairs[:, 0]))
    s = pairs[by]
    symbol = np.empty(len(by), np.int64)
    symbol[by] = np.concatenate(([1], 1 + np.cumsum((s[1:] != s[:-1]).any(axis=1))))
    symbols = np.zeros(total, np.int64)
    symbols[real] = symbol
    cuts = [*first[::SHARD].tolist(), total]
    shards = [bwt.Shard(symbols[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]
    of, start, shared = bwt.merge(shards, depth)
    same = shared >= depth  # with the row above
    interval = np.cumsum(~same)
    inside = same | np.concatenate((same[1:], [False]))
    inside[:len(bufs)] = False  # rows of end marks
    rows = np.flatnonzero(inside)
    if not len(rows):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    suffix = np.array(cuts)[of[rows]] + start[rows]
    ctx = owner[suffix]
    a = lead[ctx] + SYMBOL * nth[suffix]  # aligned place within the context
    interval = interval[rows]
    base = at[ctx] + a
    sides = np.concatenate((np.lib.stride_tricks.sliding_window_view(data, SYMBOL)[base - SYMBOL], np.lib.stride_tricks.sliding_window_view(data, ends)[base + depth * SYMBOL]), axis=1)
    windows = np.array(windows)
    found_ctx, found_at = [], []
    for j in range(SYMBOL):
        p = a - j
        ok = np.flatnonzero((p >= 0) & (p < windows[ctx]))
        if len(ok) < 2:
            continue
        edge = np.zeros((len(ok), -(-ends // 8) * 8), np.uint8)
        edge[:, :ends] = sides[ok, SYMBOL - j:SYMBOL - j + ends]
        edge = edge.view(np.uint64)
        order = np.lexsort((*edge.T, interval[ok]))
        e, i = edge[order], interval[ok][order]
        eq = (e[1:] == e[:-1]).all(axis=1) & (i[1:] == i[:-1])
        hit = np.zeros(len(ok), bool)
        hit[1:] |= eq
        hit[:-1] |= eq
        sel = ok[order[hit]]
        found_ctx.append(ctx[sel])
        found_at.append(p[sel])
    if not found_ctx:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(found_ctx), np.concatenate(found_at)


def merged_ranges(sent: DataFrame, length: int) -> DataFrame:
    """doc_id, key, s, e: byte ranges covered by windows that repeat, for contexts dealt by (fp, lo, hi)."""
    schema = "doc_id long, key long, s long, e long"
    dealt = sent.repartition("fp", "lo", "hi").sortWithinPartitions("fp", "lo", "hi")

    def run(batches):
        rows, last, out = [], None, []

        def close():
            ctx, p = repeated_windows([r[5] for r in rows], [r[3] for r in rows], [r[4] for r in rows], length)
            if not len(ctx):
                return
            order = np.lexsort((p, ctx))
            ctx, p = ctx[order], p[order]
            new = np.concatenate(([True], (ctx[1:] != ctx[:-1]) | (p[1:] > p[:-1] + 1)))
            lo = np.flatnonzero(new)
            hi = np.concatenate((lo[1:] - 1, [len(p) - 1]))
            for c, x, y in zip(ctx[lo].tolist(), p[lo].tolist(), p[hi].tolist(), strict=True):
                doc, key, start = rows[c][:3]
                out.append((doc, key, start + x, start + y + length))

        def batch_of():
            cols = list(zip(*out, strict=True))
            out.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["doc_id", "key", "s", "e"])

        for batch in batches:
            cols = [common.column_of(batch, c).to_pylist() for c in ("fp", "lo", "hi", "doc_id", "key", "start", "windows", "place", "data")]
            for fp, lo, hi, *rest in zip(*cols, strict=True):
                if (fp, lo, hi) != last:
                    if len(rows) >= CHUNK or rows and (lo, hi) != last[1:]:
                        close()
                        rows = []
                    last = (fp, lo, hi)
                rows.append(rest)
            if len(out) > 10_000:
                yield batch_of()
        if rows:
            close()
        if out:
            yield batch_of()
        common.tidy()

    return dealt.mapInArrow(run, schema)


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id, key, data: a row is told by its doc_id and the hash of both."""
    return docs.select("doc_id", F.xxhash64("doc_id", "text").alias("key"), F.col("text").cast("binary").alias("data"))


def repeated_ranges(docs: DataFrame, *, length: int = LENGTH, gram: int = GRAM, group: int = GROUP, words: int | None = None) -> DataFrame:
    """doc_id, key, ranges array<struct<s, e>> (bytes, with words: of the codes; may overlap) for the rows that lose bytes."""
    if words is not None:
        length = words * WORD
    elif length % SYMBOL:
        raise ValueError("length must be a multiple of 16")
    if length < 3 * SYMBOL or length <= gram:
        raise ValueError("length must be at least 48 and above gram")
    docs, by_word = keyed(docs), words is not None
    spark = docs.sparkSession
    anchors = each_context(docs, lambda doc, key, data, found: {"fp": found[0].view(np.int64)}, "fp long", length, gram, by_word)
    often = sketch(anchors.groupBy("fp").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("fp"))
    found = common.stored(listed_contexts(docs, often, length, gram, by_word), "contexts")
    often.destroy()
    distinct = common.stored(found.groupBy("fp", "digest").agg(F.count(F.lit(1)).alias("c"), F.min("u").alias("u")), "distinct")
    whole = common.met(found, distinct.filter("c > 1").select("fp", "digest", "c"), ["fp", "digest"], "c", found.count(), group).select("doc_id", "key", "s", "e")
    kinds = distinct.groupBy("fp").agg(F.count(F.lit(1)).alias("kinds")).filter("kinds > 1")
    some = common.stored(common.met(distinct.select("u", "fp"), kinds, ["fp"], "kinds", distinct.count(), group), "several")
    sent = sent_contexts(docs, sketch(some.select("u")), length, gram, by_word)
    hot = some.filter(F.col("kinds") > group).groupBy("fp").agg(F.ceil(F.first("kinds") / group).cast("int").alias("nb"))
    if hot.count() <= HOT_ANCHORS:
        hot = F.broadcast(hot)
    sent = sent.join(hot, "fp", "left").withColumn("nb", F.coalesce("nb", F.lit(1)))
    sent = sent.withColumn("blk", F.pmod(F.col("u"), F.col("nb")).cast("int")).withColumn("o", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)))
    sent = sent.select("fp", F.least("blk", "o").alias("lo"), F.greatest("blk", "o").alias("hi"), "doc_id", "key", "start", "windows", "place", "data")
    fine = merged_ranges(sent, length)
    return whole.unionByName(fine).groupBy("doc_id", "key").agg(F.collect_set(F.struct("s", "e")).alias("ranges"))


def spans(ranges: list | None) -> list[tuple[int, int]]:
    """Maximal runs covered by the ranges."""
    out: list[list[int]] = []
    for r in sorted((r["s"], r["e"]) for r in ranges or ()):
        if out and r[0] <= out[-1][1]:
            out[-1][1] = max(out[-1][1], r[1])
        else:
            out.append(list(r))
    return [tuple(x) for x in out]


def without(data: bytes, cut: list[tuple[int, int]]) -> bytes:
    at, parts = 0, []
    for s, e in cut:
        parts.append(data[at:s])
        at = e
    return b"".join([*parts, data[at:]])


def without_words(text: str, ranges: list, words: int) -> str:
    """text without the runs of whole words in ranges of its codes."""
    whole = [{"s": -(-r["s"] // WORD), "e": r["e"] // WORD} for r in ranges]
    start, end, _ = word_spans(text)
    cut = [(int(start[s]), int(end[e - 1])) for s, e in spans([r for r in whole if r["e"] - r["s"] >= words])]
    at, parts = 0, []
    for s, e in cut:
        parts.append(text[at:s])
        at = e
    return "".join([*parts, text[at:]])


def with_ranges(docs: DataFrame, ranges: DataFrame, name: str, free, schema) -> tuple[DataFrame, DataFrame]:
    """(what the function free makes of batches of rows that surely have no ranges, the other rows with their ranges or null in column ``name``).

    Only the others are exchanged.
    """
    key, doc = common.spare(docs, "key"), common.spare(docs, "doc")
    ranges = common.stored(ranges, "ranges")
    some = sketch(ranges.select("key"))
    keyed_docs = docs.withColumn(key, F.xxhash64("doc_id", "text"))

    def those(wanted: bool):
        def run(batches):
            for batch in batches:
                hit = passes(some, common.column_of(batch, key).to_numpy())
                batch = batch.filter(pa.array(hit if wanted else ~hit))
                yield batch if wanted else free(batch.select([c for c in batch.schema.names if c != key]))
            common.tidy()

        return run

    r = ranges.select(F.col("doc_id").alias(doc), F.col("key").alias(f"{key}2"), F.col("ranges").alias(name))
    joined = keyed_docs.mapInArrow(those(True), keyed_docs.schema).join(r, F.col("doc_id").eqNullSafe(F.col(doc)) & (F.col(key) == F.col(f"{key}2")), "left").drop(doc, f"{key}2", key)
    return keyed_docs.mapInArrow(those(False), schema), joined


REPORT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def removal_report(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for every row."""

    def report(batch: pa.RecordBatch, ranges: list):
        out = {k: [] for k in ("n_bytes", "n_removed", "n_spans", "kept_sha256")}
        for text, r in zip(common.texts_of(batch), ranges, strict=True):
            data, cut = (text or "").encode("utf-8", "surrogatepass"), spans(r)
            for k, v in zip(out, (len(data), sum(e - s for s, e in cut), len(cut), hashlib.sha256(without(data, cut)).hexdigest()), strict=True):
                out[k].append(v)
        return {"doc_id": common.column_of(batch, "doc_id")} | out

    def free(batch: pa.RecordBatch) -> pa.RecordBatch:
        made = report(batch, [None] * batch.num_rows)
        return pa.RecordBatch.from_arrays([pa.array(v, pa.string() if k == "kept_sha256" else pa.int64()) for k, v in made.items()], names=list(made))

    docs = docs.select("doc_id", "text")
    without_ranges, joined = with_ranges(docs, repeated_ranges(docs, **options), "ranges", free, REPORT)
    return without_ranges.unionByName(common.arrow_map(joined, lambda batch: report(batch, common.column_of(batch, "ranges").to_pylist()), REPORT))


def drop_repeats(docs: DataFrame, *, words: int | None = None, **options) -> DataFrame:
    """docs without the repeated bytes, with words: without the repeated runs of that many words; all columns.

    n_chars is counted anew, rows left without a word go. A character of which some bytes go is dropped whole. Rows that lose nothing are kept as they are, empty ones too.
    """
    names, schema, mark = docs.columns, docs.schema, common.spare(docs, "ranges")
    whole, joined = with_ranges(docs, repeated_ranges(docs.select("doc_id", "text"), words=words, **options), mark, lambda batch: batch, schema)

    def run(batches):
        for batch in batches:
            ranges = common.column_of(batch, mark).to_pylist()
            batch = batch.select([c for c in batch.schema.names if c != mark])
            texts = common.texts_of(batch)
            keep = [True] * len(texts)
            for i, r in enumerate(ranges):
                if r and words is not None:
                    old_text, texts[i] = texts[i], without_words(texts[i], r, words)
                    keep[i] = bool(texts[i].strip()) or texts[i] == old_text
                elif r:
                    texts[i] = without(texts[i].encode(), spans(r)).decode(errors="ignore")
                    keep[i] = bool(texts[i].strip())
            at = batch.schema.get_field_index("text")
            batch = batch.set_column(at, batch.schema.field(at), pa.array(texts, batch.schema.field(at).type))
            if "n_chars" in names:
                at = batch.schema.get_field_index("n_chars")
                old = batch.column(at).to_pylist()
                counts = [len(t) if r else o for t, r, o in zip(texts, ranges, old, strict=True)]
                batch = batch.set_column(at, batch.schema.field(at), pa.array(counts, batch.schema.field(at).type))
            yield batch.filter(pa.array(keep, pa.bool_()))
        common.tidy()

    return whole.unionByName(joined.mapInArrow(run, schema).select(*names))


def op8_suffix_dedup(spark, sf_dir):
    return removal_report(common.documents(spark, sf_dir))
