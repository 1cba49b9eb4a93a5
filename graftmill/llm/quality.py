"""Quality rules as a short-circuit cascade.

Each rule has a predicate over a document's lazily computed features. On a bounded sample the
cascade measures what each rule costs and how often it rejects, then runs the rules by rejections
per second, best first, and stops at the first rejection. The verdict is the conjunction of all
rules, so the order changes the time and never the result.

Defined results: null and empty text have no words and fail the base rule; words are runs of
anything but the six ASCII white-space characters; repeated rows are judged alike; an empty table
gives an empty table; other columns are ignored.
"""

import functools
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

#: Rows of the sample on which cost and selectivity are measured.
SAMPLE_ROWS = 512
# Fixed values of the contract.
SYMBOLS = "#*$%&|<>"
SPACES = "\t\n\x0b\x0c\r "


class Page:
    """Features of one text, computed when first asked for."""

    def __init__(self, text):
        self.text = text or ""
        self.words = self.text.encode("utf-8", "surrogatepass").split()
        self.n_words = len(self.words)

    def word_chars(self):
        return len(self.text) - sum(map(self.text.count, SPACES))

    def n_symbols(self):
        return sum(map(self.text.count, SYMBOLS))

    @functools.cached_property
    def lines(self):
        return [x for x in self.text.split("\n") if x.strip(SPACES)]

    def n_dup_lines(self):
        lines = self.lines
        return len(lines) - len(set(lines))

    def n_repeat_words(self):
        n = self.n_words
        if n < 4:
            return 0
        ids = {}
        for w in self.words:
            ids.setdefault(w, len(ids))
        if len(ids) == n:
            return 0
        a = np.fromiter(map(ids.__getitem__, self.words), np.int64, n)
        v = len(ids)
        if v < 2_000_000:
            key = (a[:-2] * v + a[1:-1]) * v + a[2:]
        else:  # three numbers no longer fit 64 bits: number the pairs first
            key = np.unique(a[:-2] * v + a[1:-1], return_inverse=True)[1] * v + a[2:]
        order = np.argsort(key, kind="stable")
        s = key[order]
        same = s[1:] == s[:-1]
        hit = np.zeros(n - 2, bool)
        hit[order[1:][same]] = True
        hit[order[:-1][same]] = True
        cover = np.zeros(n, bool)
        cover[:-2] |= hit
        cover[1:-1] |= hit
        cover[2:] |= hit
        return int(cover.sum())


def word_length(p):
    return 2 * p.n_words <= p.word_chars() <= 14 * p.n_words


def few_symbols(p):
    return 10 * p.n_symbols() <= p.n_words


def few_dup_lines(p):
    lines = p.lines
    return 10 * (len(lines) - len(set(lines))) <= 3 * len(lines)


def lower_case(p):
    letters = sum(map(str.isalpha, p.text))
    return 2 * sum(map(str.isupper, p.text)) <= letters


def wordy(p):
    """At least six words in ten hold a letter."""
    return 10 * sum(1 for w in p.words if any(map(str.isalpha, w.decode("utf-8", "replace")))) >= 6 * p.n_words


def varied(p):
    """No single word makes up more than three tenths of the text."""
    counts = {}
    for w in p.words:
        counts[w] = counts.get(w, 0) + 1
    return 10 * max(counts.values(), default=0) <= 3 * p.n_words


def few_ellipses(p):
    lines = p.lines
    return 10 * sum(x.rstrip(SPACES).endswith(("...", "…")) for x in lines) <= 3 * len(lines)


RULES = {"word_length": word_length, "few_symbols": few_symbols, "few_dup_lines": few_dup_lines, "lower_case": lower_case, "wordy": wordy, "varied": varied, "few_ellipses": few_ellipses}


def profile(docs: DataFrame, rules: dict = RULES, sample_rows: int = SAMPLE_ROWS) -> list[dict]:
    """Seconds and rejections of each rule over a sample of about ``sample_rows`` rows, drawn row by row; measured on the executors that hold them."""
    n = docs.count()
    sample = docs.select("text").sample(fraction=min(1.0, sample_rows / max(n, 1)), seed=17)

    def measure(batch: pa.RecordBatch):
        pages = [Page(x) for x in common.texts_of(batch)]
        out = {"rule": [], "rows": [], "rejected": [], "seconds": []}
        for name, rule in rules.items():
            began = time.perf_counter()
            rejected = sum(not rule(p) for p in pages)
            for k, v in (("rule", name), ("rows", len(pages)), ("rejected", rejected), ("seconds", time.perf_counter() - began)):
                out[k].append(v)
        return out

    made = common.arrow_map(sample, measure, "rule string, rows long, rejected long, seconds double")
    return [r.asDict() for r in made.groupBy("rule").agg(F.sum("rows").alias("rows"), F.sum("rejected").alias("rejected"), F.sum("seconds").alias("seconds")).collect()]


def ordered(measured: list[dict], rules: dict = RULES) -> list[str]:
    """Rules by rejections per second, best first; unmeasured ones last; ties by name."""
    worth = {m["rule"]: m["rejected"] / max(m["seconds"], 1e-9) for m in measured}
    return sorted(rules, key=lambda name: (-worth.get(name, -1.0), name))


def judge(docs: DataFrame, *, rules: dict = RULES, order: list[str] | None = None, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, the base counts, base_failed, kept, rule (the first that rejected in the order used, else null)."""
    order = order or ordered(profile(docs, rules, sample_rows), rules)
    chain = [(name, rules[name]) for name in order]

    def run(batch: pa.RecordBatch):
        out = {k: [] for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "rule")}
        for text in common.texts_of(batch):
            p = Page(text)
            row = [p.n_words, p.word_chars(), p.n_symbols(), p.n_dup_lines(), p.n_repeat_words()]
            base = p.n_words < 50 or 100 * row[4] > 50 * p.n_words
            first = None if base else next((name for name, rule in chain if not rule(p)), None)
            for k, v in zip(out, [*row, base, not base and first is None, "base" if base else first], strict=True):
                out[k].append(v)
        return out | {"doc_id": common.column_of(batch, "doc_id")}

    return common.arrow_map(docs.select("doc_id", "text"), run, "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, rule string")


def op6_quality_cascade(spark, sf_dir):
    out = judge(common.documents(spark, sf_dir))
    return out.drop("rule")  # which rule came first depends on measured times; the verdict does not
