"""Token ids by the tokenizers library, with a cache of chunks.

Both tokenizer files cut a text into words before they merge, so the ids of a text are the ids of
its chunks in order, as long as chunks are cut where the tokenizer cuts too. Every distinct chunk is
encoded by the library once for each worker and kept as ids.
A chunk that the rules below cannot cut safely is encoded whole.
"""

import array
import os
import re
import sys
import unicodedata

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from . import common

#: Chunks kept by a worker unless its encoder is given another number. Common ones come early; beyond this number new ones are encoded each time, which only costs time.
CACHE_CHUNKS = 300_000
#: Byte-level vocabularies write each byte as a printable letter: printable Latin-1 as itself, the rest from U+0100 on.
_PLAIN = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
BYTE_LETTERS = {b: b for b in _PLAIN} | {b: 256 + i for i, b in enumerate(b for b in range(256) if b not in _PLAIN)}
BYTE_SPACE = chr(BYTE_LETTERS[32])
PUNCTUATION = frozenset(".,;:!?")
#: Text taken at a time.
SLICE_BYTES = 3_000_000

assert sys.byteorder == "little"


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def loaded(path: str):
    cache = common.process_cache("tokenizers")
    if path not in cache:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        cache[path] = Tokenizer.from_file(path)
    return cache[path]


class Chunks(dict):
    """chunk -> its number; the ids of all chunks lie one after another.

    Where the vocabulary has spaces, a chunk stands for itself behind one space, and behind GLUE for itself alone.
    """

    def __init__(self, path: str, fold: bool):
        super().__init__()
        self.most = None
        self.tokenizer = loaded(path)
        self.model = self.tokenizer.model
        self.fold = fold  # the tokenizer lower-cases and drops white space
        self.store, self.first = array.array("I"), array.array("q", [0])

    def ids(self, chunk: str) -> array.array:
        number = self[chunk]
        return self.store[self.first[number]:self.first[number + 1]]

    def cut_back(self) -> None:
        """Forget the chunks beyond the first ones that are kept."""
        most = CACHE_CHUNKS if self.most is None else self.most
        while len(self) > most:
            self.popitem()
        del self.first[len(self) + 1:]
        del self.store[self.first[-1]:]

    def word(self, core: str, space: str = "") -> list[int]:
        """ids of one run of letters, with its leading space where the vocabulary has spaces: one piece for the merges."""
        if not core.isascii():
            core = core.encode().decode("latin-1").translate(BYTE_LETTERS)
        return [t.id for t in self.model.tokenize(space + core)]

    def folded(self, word: str) -> str | None:
        """The word as the tokenizer's normalizer gives it, letter by letter; None if that is not plain."""
        if word.isascii():
            return word.lower()
        low = "".join(map(str.lower, word))  # a final sigma stays a sigma, unlike in word.lower()
        return low if len(low) == len(word) and low.isalpha() and unicodedata.is_normalized("NFC", word) else None

    def made(self, chunk: str):
        if self.fold:
            if chunk.isalpha():
                low = self.folded(chunk)
                if low is not None:
                    return self.word(low) if low == chunk else self.ids(low)
            return self.tokenizer.encode(chunk, add_special_tokens=False).ids
        bare, space = (chunk[1:], "") if chunk[:1] == GLUE else (chunk, " ")
        if bare.isalpha():
            return self.word(bare, BYTE_SPACE if space else "")
        return self.tokenizer.encode(space + bare, add_special_tokens=False).ids

    def __missing__(self, chunk: str) -> int:
        ids = self.made(chunk)  # may add the lower-cased word first
        number = self[chunk] = len(self)
        self.store.extend(ids)
        self.first.append(len(self.store))
        return number


# White space as the tokenizers' patterns have it, fixed; the first class lacks the plain space.
BREAKS = r"\t-\r\x1c-\x1f\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}"
ODD_SPACES = rf"[{BREAKS}] | [{BREAKS}]|  |[{BREAKS}][{BREAKS}]|\x1f|\A[{BREAKS} ]|[{BREAKS} ]\z"
RUNS = re.compile(r"\s*\S+|\s+")
LETTERS = r"[A-Za-z\x{c0}-\x{d6}\x{d8}-\x{f6}\x{f8}-\x{ff}]"
#: A letter and a single mark behind it always belong to different pieces.
MARKED = rf"({LETTERS})([.,;:!?])( |\z)"
#: Where the vocabulary has spaces, so do a letter and a run of marks up to the next space. None of these runs is the end of a special token, which is "|>".
MARKED_BY_RUN = rf"({LETTERS})([.,;:!?#*$%&]+|\|+|<+|>+)( |\z)"
#: Stands before what has no space before it; texts that hold it go the other way.
GLUE = "\x1f"


def encoder(path: str, fold: bool, most: int | None = None):
    """A function from an Arrow array of texts to (ids of all texts one after another, number of ids of each text); ``most`` chunks are kept.

    Texts are taken in slices of about SLICE_BYTES. The words of a slice are numbered by Arrow, each distinct one is looked up
    (or encoded) once, and the ids are gathered.
    """
    cache = common.process_cache("chunks")
    if path not in cache:
        cache[path] = Chunks(path, fold)
    chunks = cache[path]
    chunks.most = most

    def words(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(numbers of the chunks of all texts, number of chunks of each), for texts whose words part at single spaces or line breaks."""
        if fold:
            texts = pc.replace_substring_regex(pc.replace_substring(texts, "\n", " "), MARKED, r"\1 \2\3")
        else:  # a line break between two other characters is a piece of its own
            texts = pc.binary_join_element_wise(*(pa.scalar(x, pa.large_string()) if isinstance(x, str) else x for x in (GLUE, pc.replace_substring(texts, "\n", f" {GLUE}\n {GLUE}"), "")))
            texts = pc.replace_substring_regex(texts, MARKED_BY_RUN, rf"\1 {GLUE}\2\3")
        lists = pc.split_pattern(texts, " ")
        flat = lists.flatten().dictionary_encode()
        distinct = flat.dictionary.to_numpy(zero_copy_only=False).tolist()  # faster than to_pylist
        numbers = np.fromiter(map(chunks.__getitem__, distinct), np.int64, len(distinct))
        return numbers[flat.indices.to_numpy()], pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)

    def runs(text: str) -> list[int]:
        """Chunks of a text with runs of white space, which stay with their word: a piece may reach across them."""
        return [chunks[c[1:] if c[0] == " " and not c[1:2].isspace() and c[1:2] not in ("", GLUE) else GLUE + c] for c in RUNS.findall(text)]

    def some(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        odd = np.zeros(len(texts), bool) if fold else pc.match_substring_regex(texts, ODD_SPACES).to_numpy(zero_copy_only=False)
        if odd.any():
            strange, (plain, many_plain) = [runs(t) for t in texts.filter(pa.array(odd)).to_pylist()], words(texts.filter(pa.array(~odd)))
            many = np.empty(len(texts), np.int64)
            many[odd], many[~odd] = [len(x) for x in strange], many_plain
            numbers, of_odd = np.empty(int(many.sum()), np.int64), np.repeat(odd, many)
            numbers[of_odd], numbers[~of_odd] = np.fromiter((n for x in strange for n in x), np.int64), plain
        else:
            numbers, many = words(texts)
        made = gathered(numbers, many)
        chunks.cut_back()
        return made

    def gathered(numbers: np.ndarray, many: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        first, store = np.frombuffer(chunks.first, np.int64), np.frombuffer(chunks.store, np.uint32)
        begin = first[numbers]
        size = first[numbers + 1] - begin
        sums = np.concatenate((np.zeros(1, np.int64), np.cumsum(size)))
        at = np.repeat(begin - sums[:-1], size)
        at += np.arange(len(at))
        ends = np.cumsum(many)
        return store[at], sums[ends] - sums[ends - many]

    def encode(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        if not len(texts):
            return np.zeros(0, np.uint32), np.zeros(0, np.int64)
        at = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False))
        cuts = np.concatenate(([0], np.flatnonzero(np.diff(at // SLICE_BYTES)) + 1, [len(texts)]))
        parts = [some(texts.slice(a, b - a)) for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]
        return tuple(np.concatenate(x) for x in zip(*parts, strict=True))

    return encode
