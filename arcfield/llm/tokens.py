"""Token ids by a public tokenizer, a group of texts at a time, each distinct word once."""

from __future__ import annotations

import hashlib
import os
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of texts whose distinct words are encoded together; letter runs that a worker remembers.
GROUP_BYTES, MAX_RUNS = 5 << 20, 250_000
#: Letters whose lower case is letters too.
LETTERS = r"[^\PL\x{130}]+"
MARKS = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
_OPEN: dict[str, WordEncoder] = {}


class Table:
    """Distinct strings and their ids in a row."""

    def __init__(self, dtype: np.dtype):
        self.values = pa.array([], pa.string())
        self.flat, self.start, self.count = np.zeros(0, dtype), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def add(self, values: pa.Array, flat: np.ndarray, count: np.ndarray) -> None:
        self.values = pa.concat_arrays([self.values, values])
        self.start = np.concatenate((self.start, len(self.flat) + np.cumsum(count) - count))
        self.count = np.concatenate((self.count, count))
        self.flat = np.concatenate((self.flat, flat))

    def find(self, values: pa.Array) -> np.ndarray:
        """Place of each value, -1 where it is new."""
        return pc.fill_null(pc.index_in(values, value_set=self.values), -1).to_numpy(zero_copy_only=False).copy()


class WordEncoder:
    """Ids of whole texts, as ``dtype``.

    The tokenizer's pre-tokenizer never joins across a blank or a line feed,
    so a text's ids are those of its blank-separated words in turn.  A word of
    letters and then ASCII marks is two pre-tokens, and case does not count:
    the letter runs of a group's distinct words that the worker does not
    remember are encoded by one call, whose ids part after the tokens that end
    a pre-token.  Marks are a small table of their own, and the few other words
    are encoded one by one.  ``_proves`` tests these properties on the tokenizer
    at hand; without them every text is encoded whole.
    """

    PROBE = "It's 12 o'clock, naïve Ünïcode\nrow two:  a--b 3.14  x \tend don't\r\n <|endoftext|> stop ÉTÉ!! Zürich's été..., (word) 日本語, ok ΣΊΣΥΦΟΣ İx ét word's' ."

    def __init__(self, content: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.tokenizer = Tokenizer.from_str(content)
        vocab = self.tokenizer.get_vocab(with_added_tokens=True)
        size = max(vocab.values()) + 1
        self.dtype = np.dtype("<u2" if size <= 1 << 16 else "<u4")
        self.ends = np.zeros(size, bool)
        self.ends[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
        # the same model for lower-case letter runs, which need no normalising and no cutting
        self.plain = Tokenizer.from_str(content)
        self.plain.normalizer = normalizers.Sequence([])
        self.plain.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        self.runs = Table(self.dtype)
        self.by_word = self._proves()

    def _whole(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, self.dtype) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _proves(self) -> bool:
        probes = [self.PROBE, self.PROBE.upper(), self.PROBE[::-1]]
        try:
            made = [self._group(pa.array([p]))[0] for p in probes]
        except ValueError:
            return False
        return all(np.array_equal(a, b) for a, b in zip(made, self._whole(probes)))

    def _listed(self, values: pa.Array) -> Table:
        """Table of values encoded one by one."""
        out, ids = Table(self.dtype), self._whole(values.to_pylist())
        if ids:
            out.add(values, np.concatenate(ids), np.array([len(x) for x in ids], np.int64))
        return out

    def _learn_runs(self, low: pa.Array) -> np.ndarray:
        """Places in ``self.runs`` of distinct lower-case runs."""
        if len(self.runs.values) > MAX_RUNS:
            self.runs = Table(self.dtype)
        at = self.runs.find(low)
        new = low.filter(pa.array(at < 0))
        if len(new):
            flat = np.array(self.plain.encode_batch_fast([" ".join(new.to_pylist())], add_special_tokens=False)[0].ids, self.dtype)
            cuts = np.flatnonzero(self.ends[flat]) + 1
            if len(cuts) != len(new):
                raise ValueError("a letter run is not one pre-token")
            at[at < 0] = np.arange(len(self.runs.values), len(self.runs.values) + len(new))
            self.runs.add(new, flat, np.diff(cuts, prepend=0))
        return at

    def _words(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids, and for each word the starts and counts of its two stretches."""
        trimmed = pc.utf8_rtrim(words, characters=MARKS)
        simple = pc.match_substring_regex(trimmed, f"^{LETTERS}$")
        letters = trimmed.filter(simple).to_pylist()
        if not unicodedata.is_normalized("NFC", " ".join(letters)):
            simple = pa.array([ok and unicodedata.is_normalized("NFC", w) for ok, w in zip(simple.to_pylist(), trimmed.to_pylist())])
        seen = pc.utf8_lower(trimmed.filter(simple)).dictionary_encode()
        run = self._learn_runs(seen.dictionary)[seen.indices.to_numpy()] if len(seen) else np.zeros(0, np.int64)
        marks = pc.struct_field(pc.extract_regex(words.filter(simple), r"(?P<m>[!-/:-@\[-`{-~]*)$"), "m").dictionary_encode()
        tails, others = self._listed(marks.dictionary), self._listed(words.filter(pc.invert(simple)))
        tail = marks.indices.to_numpy()
        is_simple = simple.to_numpy(zero_copy_only=False)
        start, count = np.zeros((len(words), 2), np.int64), np.zeros((len(words), 2), np.int64)
        start[is_simple, 0], count[is_simple, 0] = self.runs.start[run], self.runs.count[run]
        start[is_simple, 1], count[is_simple, 1] = len(self.runs.flat) + tails.start[tail], tails.count[tail]
        start[~is_simple, 0], count[~is_simple, 0] = len(self.runs.flat) + len(tails.flat) + others.start, others.count
        return np.concatenate((self.runs.flat, tails.flat, others.flat)), start, count

    def _group(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and their bounds."""
        parts = pc.split_pattern(pc.replace_substring(texts, "\n", " "), " ")
        seen = parts.flatten().dictionary_encode()
        flat, start, count = self._words(seen.dictionary)
        at = seen.indices.to_numpy()
        n = count[at].ravel()
        ends = np.cumsum(n)
        first = (start[at].ravel() - (ends - n)).astype(np.int32)
        tokens = flat[np.repeat(first, n) + np.arange(ends[-1] if len(ends) else 0, dtype=np.int32)]
        bounds = parts.offsets.to_numpy()
        return tokens, np.concatenate(([0], ends))[2 * (bounds - bounds[0])]

    def encode_arrow(self, texts: pa.Array) -> Iterator[np.ndarray]:
        """Ids of each text, group by group; a null text has none."""
        texts = pc.fill_null(texts, "")
        size = np.cumsum(pc.binary_length(texts).to_numpy().astype(np.int64))
        k = 0
        while k < len(texts):
            end = max(k + 1, int(np.searchsorted(size, (size[k - 1] if k else 0) + GROUP_BYTES)))
            group = texts.slice(k, end - k)
            try:
                if not self.by_word:
                    raise ValueError
                tokens, bounds = self._group(group)
                made = np.split(tokens, bounds[1:-1])
            except ValueError:
                made = self._whole(group.to_pylist())
            yield from made
            k = end

    def encode_many(self, texts) -> list[np.ndarray]:
        return list(self.encode_arrow(pa.array(list(texts), pa.string())))


def encoder(content: str) -> WordEncoder:
    """The worker's encoder for the tokenizer file ``content``."""
    key = hashlib.sha256(content.encode()).hexdigest()
    if key not in _OPEN:
        _OPEN[key] = WordEncoder(content)
    return _OPEN[key]


def read_tokenizer(path: str) -> str:
    with open(path, encoding="utf-8") as f:
        return f.read()


def tidy() -> None:
    """Give a worker's free memory back: it waits for its next task beside others."""
    import ctypes

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library has no such call
        pass
