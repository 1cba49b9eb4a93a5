"""Language identification by cross-parsing entropy.

For every language a suffix automaton is built over a bounded reference text. A document is parsed
greedily into the longest phrases that occur in the reference; the phrase count, normalised to
bits per character (phrases x log2(reference length) / characters), estimates the cross-entropy of
the document under the language. The language with the fewest bits wins; ties go to the first
name in order.

The automaton is turned into one complete transition table per language: where a phrase ends, the
entry leads to where the next phrase goes on and carries a mark. Parsing is then one look-up for
each character, done for all texts of a batch side by side. Texts are parsed in blocks of
BLOCK_CHARS characters, each starting a new phrase, so a very long text costs no more a character.

Bounds of the sample that is fitted (documented parameters): at most REFERENCE_DOCS whole labelled
documents of each language, in hashed order, until REFERENCE_CHARS characters. All documents are
predicted from their whole texts.

Defined results: null text, and text without a letter, gives ``und`` with score 0; without any
labelled text every document is ``und``; an empty table gives an empty table; other columns are
ignored; repeated rows are predicted alike. The score is the relative lead of the winner over the
runner-up, in [0, 1]; with a single language it is 1.
"""

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common

REFERENCE_DOCS = 64
REFERENCE_CHARS = 24_000
BLOCK_CHARS = 512
UND = "und"
#: Texts parsed side by side, in characters; about 100 bytes each at the peak.
SLICE_CHARS = 250_000


def letters_only(text: str) -> str:
    """Lower case, every run of non-letters one space."""
    return "".join(c if c.isalpha() else " " for c in text.lower())


def reference_texts(docs: DataFrame, per_lang_docs: int = REFERENCE_DOCS, per_lang_chars: int = REFERENCE_CHARS) -> dict[str, str]:
    """lang -> reference text from labelled documents outside the held-out third."""
    doc = F.col("doc_id").cast("string")
    rows = docs.select("doc_id", "text", "lang").filter("lang is not null and text is not null and doc_id is not null").filter(F.crc32(doc) % 3 != 1)
    w = Window.partitionBy("lang").orderBy(F.md5(doc), "doc_id", "text")
    some = rows.withColumn("__r", F.row_number().over(w)).filter(F.col("__r") <= per_lang_docs).collect()
    out: dict[str, str] = {}
    for r in sorted(some, key=lambda r: (r["lang"], r["__r"])):
        have = out.setdefault(r["lang"], "")
        if len(have) < per_lang_chars:
            out[r["lang"]] = (have + " " + " ".join(letters_only(r["text"]).split()))[: per_lang_chars]
    return {k: v for k, v in out.items() if v.strip()}


def suffix_automaton(symbols) -> list[dict]:
    """Transitions of the minimal automaton of all substrings; state 0 is the start."""
    length, link, step, last = [0], [-1], [{}], 0
    for c in symbols:
        cur = len(step)
        length.append(length[last] + 1)
        link.append(0)
        step.append({})
        p = last
        while p != -1 and c not in step[p]:
            step[p][c] = cur
            p = link[p]
        if p != -1:
            q = step[p][c]
            if length[p] + 1 == length[q]:
                link[cur] = q
            else:
                twin = len(step)
                length.append(length[p] + 1)
                link.append(link[q])
                step.append(dict(step[q]))
                while p != -1 and step[p].get(c) == q:
                    step[p][c] = twin
                    p = link[p]
                link[q] = link[cur] = twin
        last = cur
    return step


class Model:
    """alphabet: code point -> symbol (0 space, 1 any other letter, 2 end of block, 3.. known letters)."""

    def __init__(self, references: dict[str, str]):
        self.langs = sorted(references)
        known = sorted({c for t in references.values() for c in t} - {" "})
        self.symbol = {" ": 0} | {c: i + 3 for i, c in enumerate(known)}
        self.width = len(known) + 3
        self.bits = [float(np.log2(max(2, len(references[x])))) for x in self.langs]
        self.tables = [self.table(suffix_automaton([self.symbol[c] for c in references[x]])) for x in self.langs]

    def table(self, step: list[dict]) -> np.ndarray:
        """entry = 4 x (row offset of the next state) + phrases that ended here.

        A symbol that the reference lacks is a phrase of its own, beside the open one that it ends.
        """
        w = self.width
        root = np.full(w, 1, np.int64)
        for c, s in step[0].items():
            root[c] = 4 * s * w
        out = np.tile(root + 1, (len(step), 1))
        out[0] = root
        for s, t in enumerate(step):
            for c, to in t.items():
                out[s, c] = 4 * to * w
        out[:, 2] = 1  # end of block: the open phrase ends
        out[0, 2] = 0
        return out.astype(np.int32).ravel()


def lookup(model: Model) -> np.ndarray:
    """code point -> symbol, with case folded for single code points; non-letters are spaces."""
    cache = common.process_cache("letters")
    if "codes" not in cache:
        lower = np.arange(0x110000, dtype=np.uint32)
        letter = np.zeros(0x110000, bool)
        for cp in range(0x110000):
            c = chr(cp)
            if c.isalpha():  # letters of every plane
                letter[cp] = True
                low = c.lower()
                lower[cp] = ord(low) if len(low) == 1 else cp
        cache["codes"] = letter, lower
    letter, lower = cache["codes"]
    by = np.where(letter, 1, 0).astype(np.uint16)
    for c, s in model.symbol.items():
        if c != " ":
            by[ord(c)] = s
    return np.where(letter, by[lower], 0).astype(np.uint16)


def phrase_counts(model: Model, codes: np.ndarray, texts: list[str], block: int = BLOCK_CHARS):
    """(characters, phrases[language, text]) of each text after folding and joining of spaces."""
    n = len(texts)
    lens = np.fromiter(map(len, texts), np.int64, n)
    cps = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
    sym = codes[np.minimum(cps, 0x10FFFF)]
    owner = np.repeat(np.arange(n), lens)
    if len(sym):  # runs of spaces become one, within a text
        keep = np.ones(len(sym), bool)
        keep[1:] = (sym[1:] != 0) | (sym[:-1] != 0) | (owner[1:] != owner[:-1])
        sym, owner = sym[keep], owner[keep]
    chars = np.bincount(owner, minlength=n)
    has_letter = np.bincount(owner, weights=sym != 0, minlength=n) > 0
    blocks = -(-chars // block)
    first = np.concatenate(([0], np.cumsum(blocks)))
    of_block = np.repeat(np.arange(n), blocks)
    grid = np.full((first[-1], block + 1), 2, np.uint16)
    at = np.arange(len(sym)) - np.repeat(np.cumsum(chars) - chars, chars)
    grid[first[owner] + at // block, at % block] = sym
    used = np.bincount(first[owner] + at // block, minlength=first[-1])
    order = np.argsort(-used, kind="stable")
    grid = np.ascontiguousarray(grid[order].T)
    live = np.searchsorted(-used[order], -np.arange(block + 1), side="right")  # blocks that still have a symbol or their end
    out = np.zeros((len(model.tables), n))
    for k, table in enumerate(model.tables):
        state = np.zeros(first[-1], np.int32)
        count = np.zeros(first[-1], np.int32)
        for i in range(block + 1):
            m = live[i]
            if not m:
                break
            e = table[state[:m] + grid[i, :m]]
            count[:m] += e & 3
            state[:m] = e >> 2
        out[k] = np.bincount(of_block[order], weights=count, minlength=n)
    return chars, has_letter, out


def predictor(model: Model, block: int = BLOCK_CHARS):
    """A function from texts to (langs, scores)."""
    codes = lookup(model) if model.langs else None

    def predict(texts: list):
        langs, scores = [UND] * len(texts), [0.0] * len(texts)
        if not model.langs:
            return langs, scores
        start = 0
        while start < len(texts):
            size, end = 0, start
            while end < len(texts) and (size == 0 or size + len(texts[end] or "") <= SLICE_CHARS):
                size += len(texts[end] or "")
                end += 1
            chars, letter, phrases = phrase_counts(model, codes, [t or "" for t in texts[start:end]], block)
            rate = phrases * np.array(model.bits)[:, None] / np.maximum(chars, 1)
            best = np.argmin(rate, axis=0)
            low = rate.min(axis=0)
            second = np.partition(rate, 1, axis=0)[1] if len(model.langs) > 1 else np.full(len(low), np.inf)
            lead = np.where(np.isinf(second), 1.0, (second - low) / np.maximum(second, 1e-12))
            for j in np.flatnonzero(letter):
                langs[start + j] = model.langs[best[j]]
                scores[start + j] = float(min(1.0, max(0.0, lead[j])))
            start = end
        return langs, scores

    return predict


def fit(docs: DataFrame, **bounds) -> Model:
    return Model(reference_texts(docs, **bounds))


def identify(docs: DataFrame, model: Model | None = None) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row."""
    model = model or fit(docs)
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the reference bounds

    def run(batch: pa.RecordBatch):
        langs, scores = predictor(shared.value)(common.texts_of(batch))
        ids = common.column_of(batch, "doc_id")
        held = [x is not None and zlib.crc32(str(x).encode()) % 3 == 1 for x in ids.to_pylist()]
        return {"doc_id": ids, "held_out": held, "lang_pred": langs, "score": scores}

    return common.arrow_map(docs.select("doc_id", "text"), run, "doc_id long, held_out boolean, lang_pred string, score double")


def keep_identified(docs: DataFrame, languages: list[str] | None = None, model: Model | None = None) -> DataFrame:
    """The rows whose language is identified (and among ``languages`` if given), all columns; a missing lang is filled in where there is such a column.

    Null and letterless texts are rejected.
    """
    names = docs.columns
    model = model or fit(docs)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = docs.schema

    def run(batches):
        common.process_cache("letters")  # drops what other operators left in this worker before the model is read
        predict = predictor(shared.value)
        for batch in batches:
            langs, _ = predict(common.texts_of(batch))
            keep = [x != UND and (languages is None or x in languages) for x in langs]
            i = batch.schema.get_field_index("lang")
            if i >= 0:
                filled = [a if a is not None else b for a, b in zip(batch.column(i).to_pylist(), langs, strict=True)]
                batch = batch.set_column(i, "lang", pa.array(filled, batch.schema.field(i).type))
            yield batch.filter(pa.array(keep, pa.bool_()))
            del batch, langs, keep
            common.tidy()

    return docs.mapInArrow(run, schema).select(*names)


def op4_language_id(spark, sf_dir):
    return identify(common.documents(spark, sf_dir))
