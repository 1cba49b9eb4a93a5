"""Semantic segmentation of documents: sentences whose encodings are alike stay together.

Everything about a document is decided where the document lies: splitting, encoding, similarity, merging and limits
are one map over Arrow batches, with no exchange. Encodings are counts of hashed character n-grams, so the threshold
test is exact in integers.

modes
    windowed           a sentence joins the running segment if it is alike to one of the previous w - 1 sentences that
                       still belongs to the segment
    adjacent           it joins if it is alike to the sentence before it
    pairs              connected groups of alike sentences of the whole document
    window_components  connected groups of alike sentences less than w apart
"""

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

DIM, GRAM, WINDOW, MAX_TOKENS, MIN_SENTENCES = 384, 2, 8, 512, 2
TAU = (1, 2)
MODES = ("windowed", "adjacent", "pairs", "window_components")
POLICIES = ("attach_prev", "attach_next", "drop", "keep")


class HashEncoder:
    """Counts of character n-grams (or words) in ``dim`` buckets: first 8 hex digits of the md5, modulo dim."""

    def __init__(self, dim: int = DIM, n: int = GRAM, unit: str = "char"):
        self.dim, self.n, self.unit, self.known = dim, n, unit, {}

    def bucket(self, gram: str) -> int:
        b = self.known.get(gram)
        if b is None:
            if len(self.known) > 200_000:
                self.known.clear()
            b = self.known[gram] = int(hashlib.md5(gram.encode()).hexdigest()[:8], 16) % self.dim
        return b

    def grams(self, text: str) -> list[str]:
        if self.unit == "word":
            return [w for w in text.lower().split(" ") if w]
        return [text[i:i + self.n] for i in range(len(text) - self.n + 1)]

    def encode(self, texts: list[str]) -> np.ndarray:
        out = np.zeros((len(texts), self.dim), np.int64)
        for row, t in enumerate(texts):
            b = [self.bucket(g) for g in self.grams(t)]
            if b:
                out[row] = np.bincount(b, minlength=self.dim)
        return out


class TfidfEncoder(HashEncoder):
    """Counts of words in buckets, each times the logarithm of how rare its bucket is; ``fit`` counts the documents of every bucket, so the model has ``dim`` numbers at any size."""

    def __init__(self, weights: np.ndarray):
        super().__init__(len(weights), 1, "word")
        self.weights = np.asarray(weights, np.float64)

    @classmethod
    def fit(cls, docs: DataFrame, dim: int = DIM) -> "TfidfEncoder":
        words = F.array_remove(F.array_distinct(F.split(F.lower("text"), " ")), "")
        bucket = F.transform(words, lambda w: (F.conv(F.substring(F.md5(w), 1, 8), 16, 10).cast("long") % dim).cast("int"))
        hit = docs.select(F.explode(F.array_distinct(bucket)).alias("b")).groupBy("b").count()
        total, df = docs.count(), np.zeros(dim)
        for b, n in hit.collect():  # one row a bucket: dim at most
            df[b] = n
        return cls(np.log((1 + total) / (1 + df)) + 1)

    def encode(self, texts: list[str]) -> np.ndarray:
        return super().encode(texts) * self.weights


class LookupEncoder:
    """The sum of given word vectors; a word that has none adds nothing, so a text without known words is a zero vector and like no other.

    The table travels with every task and must stay below MOST words.
    """

    MOST = 200_000

    def __init__(self, vectors: dict[str, list[float]]):
        if not vectors or len(vectors) > self.MOST or len({len(v) for v in vectors.values()}) != 1:
            raise ValueError(f"1 to {self.MOST} vectors of one length are needed")
        self.vectors = {w.lower(): np.asarray(v, np.float64) for w, v in vectors.items()}
        self.dim = len(next(iter(self.vectors.values())))

    def encode(self, texts: list[str]) -> np.ndarray:
        out = np.zeros((len(texts), self.dim))
        for row, t in enumerate(texts):
            for w in t.lower().split(" "):
                if w in self.vectors:
                    out[row] += self.vectors[w]
        return out


def split_sentences(text) -> list[str]:
    out = [""]
    for c in text or "":
        if c in ".!?\n":
            out.append("")
        else:
            out[-1] += c
    return [s for s in (x.strip(" ") for x in out) if s]


def token_count(sentence: str) -> int:
    return len([w for w in sentence.split(" ") if w])


def alike(x: np.ndarray, lag: int, tau=TAU, strict: bool = False) -> np.ndarray:
    """Whether sentence i + lag is alike to sentence i."""
    d = (x[lag:] * x[:-lag]).sum(axis=1)
    n = (x * x).sum(axis=1)
    left, right = tau[1] ** 2 * d * d, tau[0] ** 2 * n[lag:] * n[:-lag]
    return (d > 0) & (left > right if strict else left >= right)


def latest_alike(x: np.ndarray, w: int, tau=TAU, strict: bool = False) -> np.ndarray:
    """For each sentence the nearest alike one among the w - 1 before it, else -1."""
    out = np.full(len(x), -1)
    for lag in range(min(w, len(x)) - 1, 0, -1):
        hit = np.flatnonzero(alike(x, lag, tau, strict)) + lag
        out[hit] = hit - lag
    return out


def labels(x: np.ndarray, mode: str, w: int, tau=TAU, strict: bool = False) -> list[int]:
    """Segment label of each sentence; labels are the first sentence of the segment."""
    n = len(x)
    if mode in ("windowed", "adjacent"):
        near = latest_alike(x, w if mode == "windowed" else 2, tau, strict)
        out, start = [], 0
        for i in range(n):
            if near[i] < start:
                start = i
            out.append(start)
        return out
    parent = list(range(n))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for lag in range(1, n if mode == "pairs" else min(w, n)):
        for i in np.flatnonzero(alike(x, lag, tau, strict)).tolist():
            a, b = root(i), root(i + lag)
            parent[max(a, b)] = min(a, b)
    return [root(i) for i in range(n)]


def groups_of(label: list[int]) -> list[list[int]]:
    out: dict[int, list[int]] = {}
    for i, g in enumerate(label):
        out.setdefault(g, []).append(i)
    return [out[g] for g in sorted(out)]


def join_short(groups: list[list[int]], least: int, policy: str) -> list[list[int]]:
    """Segments below ``least`` sentences are attached to a neighbour, dropped or kept."""
    if policy == "keep":
        return groups
    if policy == "drop":
        return [g for g in groups if len(g) >= least]
    out: list[list[int]] = []
    for g in groups if policy == "attach_prev" else reversed(groups):
        if len(g) < least and out:
            out[-1] = sorted(out[-1] + g)
        elif out and len(out[-1]) < least:  # the first one was short itself
            out[-1] = sorted(out[-1] + g)
        else:
            out.append(g)
    return out if policy == "attach_prev" else out[::-1]


def cap(groups: list[list[int]], sizes: list[int], most: int, how: str) -> list[list[int]]:
    """Split segments so that none holds more than ``most`` tokens (greedy), or by running total / most (bucket)."""
    out = []
    for g in groups:
        part, total, run = [], 0, 0
        for i in g:
            new = part and (total + sizes[i] > most if how == "greedy" else run // most != (run + sizes[i]) // most)
            if new:
                out.append(part)
                part, total = [], 0
            part.append(i)
            total += sizes[i]
            run += sizes[i]
        if part:
            out.append(part)
    return out


def hard_split(sentences: list[str], most: int) -> list[str]:
    """A sentence longer than the cap becomes several."""
    out = []
    for s in sentences:
        w = [x for x in s.split(" ") if x]
        out += [s] if len(w) <= most else [" ".join(w[k:k + most]) for k in range(0, len(w), most)]
    return out


def segment(docs: DataFrame, *, mode: str = "windowed", w: int = WINDOW, tau=TAU, strict: bool = False, min_sents: int = MIN_SENTENCES, max_tokens: int = MAX_TOKENS, short_policy: str = "attach_prev", cap_how: str = "greedy", encoder: HashEncoder | LookupEncoder | None = None, limits: bool = True) -> DataFrame:
    """doc_id, seg_no, first_sent, last_sent, n_sents, n_tok, cap_orphan, text of each segment.

    limits=False gives the bare groups of the mode. A segment that the cap leaves with fewer than min_sents sentences is marked cap_orphan.
    """
    if mode not in MODES or short_policy not in POLICIES or cap_how not in ("greedy", "bucket"):
        raise ValueError("unknown mode, policy or cap")
    encoder = encoder or HashEncoder()
    names = ("doc_id", "seg_no", "first_sent", "last_sent", "n_sents", "n_tok", "cap_orphan", "text")

    def run(batches):
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                sents = split_sentences(text)
                if limits:
                    sents = hard_split(sents, max_tokens)
                if not sents:
                    continue
                sizes = [token_count(s) for s in sents]
                groups = groups_of(labels(encoder.encode(sents), mode, w, tau, strict))
                if limits:
                    groups = cap(join_short(groups, min_sents, short_policy), sizes, max_tokens, cap_how)
                for k, g in enumerate(groups):
                    rows.append((doc, k, g[0], g[-1], len(g), sum(sizes[i] for i in g), len(g) < min_sents, ". ".join(sents[i] for i in g)))
            if rows:
                kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.bool_(), pa.string())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=list(names))

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, seg_no int, first_sent int, last_sent int, n_sents int, n_tok long, cap_orphan boolean, text string")


def similarity_flags(docs: DataFrame, *, w: int = WINDOW, tau=TAU, encoder: HashEncoder | LookupEncoder | None = None) -> DataFrame:
    """doc_id, sent_no, latest: nearest alike sentence among the w - 1 before (-1: none)."""
    encoder = encoder or HashEncoder()

    def run(batches):
        for batch in batches:
            out = [[], [], []]
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                sents = split_sentences(text)
                if sents:
                    out[0] += [doc] * len(sents)
                    out[1] += range(len(sents))
                    out[2] += latest_alike(encoder.encode(sents), w, tau).tolist()
            if out[0]:
                yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int32()), pa.array(out[2], pa.int32())], names=["doc_id", "sent_no", "latest"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, sent_no int, latest int")


def encoded(docs: DataFrame, *, encoder: HashEncoder | None = None) -> DataFrame:
    """Sparse encodings of an encoder that counts: doc_id, sent_no, bucket, n."""
    encoder = encoder or HashEncoder()

    def run(batches):
        for batch in batches:
            out = [[], [], [], []]
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                sents = split_sentences(text)
                if not sents:
                    continue
                x = encoder.encode(sents)
                row, col = np.nonzero(x)
                out[0] += [doc] * len(row)
                out[1] += row.tolist()
                out[2] += col.tolist()
                out[3] += x[row, col].tolist()
            if out[0]:
                yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int32()), pa.array(out[2], pa.int32()), pa.array(out[3], pa.int64())], names=["doc_id", "sent_no", "bucket", "n"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, sent_no int, bucket int, n long")
