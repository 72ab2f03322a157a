"""Token ids of whole texts by a public tokenizer, at the speed of its distinct words.

Both vocabularies split a text before every white-space run and between letters
and punctuation, so the ids of a text are the ids of its chunks in order.  Each distinct chunk is
encoded once by the tokenizers library and remembered (bounded memory); texts
with white space other than blank and line feed, and texts that hold a special
token's name, go to the library whole, which reads such a name as that token.
"""

from __future__ import annotations

import itertools
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import ragged

#: A word of plain letters ends before common punctuation; else what stands up to the next blank or line feed.
CHUNK = re.compile(r"[ \n]*[A-Za-zÀ-ÖØ-öø-ÿ]+(?=[.,!?:;#*$%&|])|[ \n]*[^ \n]+|[ \n]+")
#: White space that the column way does not take: doubled, leading, trailing, or of other kinds (RE2 syntax).
_OTHERS = r"[\x00-\x09\x0b-\x1f\x7f\x{85}\x{a0}\x{1680}\x{2000}-\x{200f}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}\x{feff}]"
ODD = r"[ \n][ \n]|^[ \n]|[ \n]\z|" + _OTHERS
ODD_LOSSY = _OTHERS
LETTER_MARK = r"([A-Za-z\x{C0}-\x{D6}\x{D8}-\x{F6}\x{F8}-\x{FF}])([.,!?:;#*$%&|])"
SIMPLE = re.compile(r" ?[^ \n]+\Z")
OTHER_SPACE = re.compile(r"[^\S \n]|[\x1c-\x1f\x85]")


def vocabulary(name: str) -> str:
    """Path of a vocabulary file of the installed public tokenizers."""
    import public_tokenizers

    return public_tokenizers.path(name)


class Encoder:
    """Encodes texts to id arrays; `lossy_space` says that the vocabulary drops white space."""

    def __init__(self, path: str, lossy_space: bool = False, remembered: int = 900_000):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        names = sorted({t.content for t in self.tok.get_added_tokens_decoder().values()})
        self.special = re.compile("|".join(map(re.escape, names)) if names else r"(?!)", re.I)
        quoted = "|".join(re.sub(r"([^A-Za-z0-9_])", r"\\\1", n) for n in names)
        self.odd = (ODD_LOSSY if lossy_space else ODD) + (f"|(?i:{quoted})" if names else "")
        self.lossy = lossy_space
        self.limit = remembered
        self.line_feed = self.tok.encode("\n", add_special_tokens=False).ids[0] if not lossy_space else -1
        self._forget()

    def _forget(self):
        self.number: dict[str, int] = {}
        self.ids = np.zeros(1 << 16, np.int32)
        self.start = np.zeros(1 << 14, np.int64)
        self.length = np.zeros(1 << 14, np.int64)
        self.used = 0

    def _encode_chunks(self, part: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the chunks one after another, and how many each has: one call for all, told apart by line feeds or by offsets."""
        if not self.lossy:  # a line feed is a token of its own, which no chunk here has
            ids = np.array(self.tok.encode_batch_fast(["\n".join(part)], add_special_tokens=False)[0].ids, np.int32)
            feed = ids == self.line_feed
            owner = np.cumsum(feed)[~feed]
            return ids[~feed], np.bincount(owner, minlength=len(part)).astype(np.int64)
        width = np.fromiter(map(len, part), np.int64, len(part)) + 1
        begin = np.cumsum(width) - width
        e = self.tok.encode(" ".join(part), add_special_tokens=False)
        ids = np.array(e.ids, np.int32)
        at = np.fromiter((o[0] for o in e.offsets), np.int64, len(ids))
        owner = np.searchsorted(begin, at, "right") - 1
        return ids, np.bincount(owner, minlength=len(part)).astype(np.int64)

    def _learn(self, new: list[str]):
        """Encode chunks not met before."""
        plain = [c for c in new if SIMPLE.match(c)]
        jobs = [(plain[i : i + 4096], True) for i in range(0, len(plain), 4096)]
        if len(plain) < len(new):
            jobs.append(([c for c in new if not SIMPLE.match(c)], False))
        for part, together in jobs:
            if together:
                flat, size = self._encode_chunks(part)
            else:
                found = [e.ids for e in self.tok.encode_batch(part, add_special_tokens=False)]
                size = np.fromiter(map(len, found), np.int64, len(found))
                flat = np.fromiter((i for f in found for i in f), np.int32, int(size.sum()))
            total, n = len(flat), len(self.number)
            while self.used + total > len(self.ids):
                self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
            while n + len(part) > len(self.start):
                self.start = np.concatenate([self.start, np.zeros_like(self.start)])
                self.length = np.concatenate([self.length, np.zeros_like(self.length)])
            self.ids[self.used : self.used + total] = flat
            self.start[n : n + len(part)] = self.used + np.cumsum(size) - size
            self.length[n : n + len(part)] = size
            self.number.update(zip(part, range(n, n + len(part))))
            self.used += total

    def encode_all(self, texts: list[str | None]) -> list[np.ndarray]:
        """Ids of each text; a run of texts is looked up and laid out together."""
        if len(self.number) > self.limit:
            self._forget()
        whole: dict[int, np.ndarray] = {}
        parts: list[list[str]] = []
        for i, t in enumerate(texts):
            if not t:
                parts.append([])
            elif not t.replace("\n", " ").isprintable() and OTHER_SPACE.search(t) or self.special.search(t):
                parts.append([])
                whole[i] = np.array(self.tok.encode(t, add_special_tokens=False).ids, np.int32)
            else:
                parts.append(CHUNK.findall(t))
        new = set().union(*parts).difference(self.number)
        if new:
            self._learn(list(new))
        count = np.fromiter(map(len, parts), np.int64, len(parts))
        codes = np.fromiter(map(self.number.__getitem__, itertools.chain.from_iterable(parts)), np.int64, int(count.sum()))
        size = self.length[codes]
        flat = self.ids[ragged(self.start[codes], size)]
        stop = np.r_[0, np.cumsum(size)][np.cumsum(count)]
        out = np.split(flat, stop[:-1]) if len(texts) else []
        for i, ids in whole.items():
            out[i] = ids
        return out

    def encode_column(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts of an Arrow column one after another, and how many each has.

        Words are split and numbered by Arrow's kernels; only a batch's distinct
        words become Python strings.  Texts whose white space is not made of single
        blanks and line feeds between words take the general way.
        """
        texts = texts.cast(pa.large_string()).fill_null("")
        odd = pc.match_substring_regex(texts, self.odd).to_numpy(zero_copy_only=False)
        plain = texts.filter(pa.array(~odd)) if odd.any() else texts
        flat, size = self._plain_column(plain)
        if not odd.any():
            return flat, size
        where = np.flatnonzero(odd)
        rest = self.encode_all([texts[int(i)].as_py() for i in where])
        sizes = np.zeros(len(texts), np.int64)
        sizes[~odd], sizes[odd] = size, [len(r) for r in rest]
        out = np.zeros(int(sizes.sum()), np.int32)
        starts = np.cumsum(sizes) - sizes
        out[ragged(starts[~odd], size)] = flat
        out[ragged(starts[odd], sizes[odd])] = np.concatenate(rest)
        return out, sizes

    def _plain_column(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        if len(self.number) > self.limit:
            self._forget()
        # Letters and the punctuation after them are set apart, so that a word is one word wherever it stands.
        if self.lossy:
            cut = pc.split_pattern(pc.replace_substring_regex(pc.ascii_lower(pc.replace_substring(texts, "\n", " ")), LETTER_MARK, r"\1 \2"), " ")
        else:
            cut = pc.split_pattern(pc.replace_substring_regex(pc.replace_substring(texts, "\n", " \n "), LETTER_MARK, "\\1 \x01\\2"), " ")
        count = pc.list_value_length(cut).to_numpy(zero_copy_only=False).astype(np.int64)
        coded = pc.list_flatten(cut).dictionary_encode()
        code = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
        words = coded.dictionary.to_pylist()
        if self.lossy:
            used = np.arange(len(words))
        else:
            # A word at a text's start or at a line feed has no blank of its own in front.
            feed = np.array([w == "\n" for w in words], bool)[code] if "\n" in words else np.zeros(len(code), bool)
            bare = feed.copy()
            bare[1:] |= feed[:-1]
            first = (np.cumsum(count) - count)[count > 0]
            bare[first] = True
            code = 2 * code + bare
            seen = np.zeros(2 * len(words), bool)
            seen[code] = True
            used = np.flatnonzero(seen)
            words = [w[1:] if w[:1] == "\x01" else w if k & 1 or not w else " " + w for k, w in ((k, words[k >> 1]) for k in used.tolist())]
        new = list(set(words).difference(self.number))
        if new:
            self._learn(new)
        table = np.zeros(2 * len(words) + 2 if self.lossy else len(seen), np.int64)
        table[used] = np.fromiter(map(self.number.__getitem__, words), np.int64, len(words))
        entry = table[code]
        size = self.length[entry]
        flat = self.ids[ragged(self.start[entry], size)]
        ends = np.r_[0, np.cumsum(size)][np.cumsum(count)] if len(count) else np.zeros(0, np.int64)
        return flat, np.diff(np.r_[0, ends])

    def encode(self, text: str | None) -> np.ndarray:
        return self.encode_all([text])[0]


def slices(batch: pa.RecordBatch, text: int, most: int = 10 << 20):
    """The batch in runs of rows with about `most` bytes of text each, at least a row."""
    size = pc.binary_length(batch.column(text)).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    run = np.cumsum(size) // most
    cut = np.r_[0, np.flatnonzero(np.diff(run)) + 1, len(size)] if len(size) else [0]
    for a, b in zip(cut[:-1], cut[1:]):
        yield batch.slice(int(a), int(b - a))


def with_end(flat: np.ndarray, size: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """The ids with an end id after each document, and the new sizes."""
    size = size + 1
    out = np.full(int(size.sum()), end_id, np.int32)
    stop = np.cumsum(size) - 1
    mask = np.ones(len(out), bool)
    mask[stop] = False
    out[mask] = flat
    return out, size


_encoders: dict[tuple, Encoder] = {}


def encoder(path: str, lossy_space: bool = False, remembered: int = 900_000) -> Encoder:
    """One encoder a worker process."""
    key = (path, lossy_space, remembered)
    if key not in _encoders:
        _encoders[key] = Encoder(path, lossy_space, remembered)
    return _encoders[key]
