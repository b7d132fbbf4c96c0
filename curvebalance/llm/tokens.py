"""Token ids of whole texts, once per worker and vocabulary.

Both encoders give exactly the ids of the tokenizers library for the vocabulary file. What most texts consist of goes a faster way: the
byte-level vocabulary by the same vocabulary's ranks, the word vocabulary by a bounded memo of white-space-separated pieces (that
vocabulary never joins across white space) in front of a ranked encoder made from the file's merges. A text with any character on which Unicode versions or libraries may differ, or with the string of a special
token, goes to the library as a whole.
"""

from __future__ import annotations

import base64
import os
import re
from functools import lru_cache

import numpy as np

from . import common as C

#: Characters on which all libraries agree; others send the text to the library as a whole.
PLAIN = re.compile("[\t\n\r\x20-\x7e¡-įı-Ɂ‐-‧‰-⁞€]*")
#: Places of a worker's memo of pieces, and the bytes of the longest piece it holds.
SLOTS, LONGEST = 1 << 20, 64
#: The word vocabulary's split of a lower-cased text (a fixed value of that file).
WORDS = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


#: The ASCII part of these characters.
ASCII = bytes([9, 10, 13, *range(32, 127)])


def plain(text: str) -> bool:
    if text.isascii():  # much faster than the pattern
        return "<|" not in text and not text.encode().translate(None, ASCII)
    return "<|" not in text and PLAIN.fullmatch(text) is not None


@lru_cache(4)
def library(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


@lru_cache(4)
def ranked(path: str):
    import public_tokenizers
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


class ByteBpe:
    """Ids of the byte-level vocabulary. `ranks`: its ranks file, or None to use the library only."""

    def __init__(self, path: str, ranks: str | None):
        self.path, self.ranks = path, ranks

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        fast = ranked(self.ranks) if self.ranks else None
        return [np.array(fast.encode_ordinary(x) if fast and plain(x) else library(self.path).encode(x, add_special_tokens=False).ids, np.uint32) for x in texts]


def byte_letters() -> list[str]:
    """The character that stands for each byte in byte-level vocabularies: visible Latin-1 ones for themselves, others from 256 up."""
    seen = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in seen]
    return [chr(b) if b in seen else chr(256 + rest.index(b)) for b in range(256)]


@lru_cache(4)
def _splitter(path: str):
    """The vocabulary's word pattern, if the file has the one that is known here; else None, and all goes to the library."""
    import json

    import regex

    with open(path, encoding="utf-8") as f:
        pre = json.load(f)["pre_tokenizer"]
    known = any(p.get("pattern") == {"Regex": WORDS} for p in pre.get("pretokenizers", ()))
    return regex.compile(WORDS) if known else None


def end_marked(vocabulary: dict[str, int], merges: list[tuple[str, str]]):
    """A ranked encoder of words that end with `END`, and for its ids the vocabulary's ids and whether a word ends there.

    The mark joins the byte before it ahead of all merges, which gives the symbol with the word-end suffix; then merges come in their order. A pair
    that can be joined is always that of its merge: bounds between symbols only vanish, so what lies between two bounds has merged as it would alone.
    """
    import tiktoken

    suffix = "</w>"
    byte = {c: i for i, c in enumerate(byte_letters())}

    def spelt(t: str) -> bytes:
        whole = t.removesuffix(suffix)
        return bytes(byte[c] for c in whole) + END.encode() * (whole != t)

    names = list(byte) + [c + suffix for c in byte] + [a + b for a, b in merges]
    ranks: dict[bytes, int] = {}
    for i, t in enumerate(names):
        ranks.setdefault(spelt(t), i)
    ids = np.array([vocabulary.get(t, 0) for t in names])
    return tiktoken.Encoding("words", pat_str=f"[^{END}]+{END}", mergeable_ranks=ranks, special_tokens={}), ids, np.array([t.endswith(suffix) for t in names])


#: Ends a word, and stands between texts; no plain text has them.
END, BREAK = "\x01", "\x0c"


class Memo:
    """Ids of lower-cased pieces between white space, looked up for all pieces of many texts at once.

    A table of `SLOTS` places, by hash, says where a piece's ids stand in a pool. A piece whose place another one has, or that is long, is
    encoded anew each time, in one call for all such pieces; the pool holds one piece a slot at most.
    """

    def __init__(self, path: str):
        import json

        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        self.split = _splitter(path).findall
        self.encoder, self.ids, self.last = end_marked(model["vocab"], [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]])
        self.key, self.start, self.count = np.zeros(SLOTS, np.uint64), np.full(SLOTS, -1, np.int64), np.zeros(SLOTS, np.int32)
        self.pool = np.zeros(0, np.uint32)

    def encode(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the pieces, one after another, and where each begins (and the last ends): their words go through the encoder in one call."""
        words, ends = [], [0]
        for w in pieces:
            if w.isalpha():
                words.append(w)
            elif w[-1] in ".,;:!?" and w[:-1].isalpha():  # letters and what follows them are words of their own
                words.append(w[:-1])
                words.append(w[-1])
            else:
                words += self.split(w)
            ends.append(len(words))
        found = np.array(self.encoder.encode_ordinary(END.join(words) + END), np.int64)
        return self.ids[found].astype(np.uint32), np.concatenate(([0], np.flatnonzero(self.last[found]) + 1))[ends]

    def texts(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of plain texts, one after another, and where each begins (and the last ends)."""
        raw = BREAK.join(texts).lower().encode()
        data = np.frombuffer(raw, np.uint8)
        off = np.concatenate(([0], np.flatnonzero(data == ord(BREAK)), [len(data)]))
        h, at, s, e = C.word_hashes(data, off, False)
        slot = (h >> np.uint64(64 - SLOTS.bit_length() + 1)).astype(np.int64)
        short = e - s <= LONGEST
        start, count = self.start[slot], self.count[slot].astype(np.int64)
        miss = np.flatnonzero((self.key[slot] != h) | (start < 0) | ~short)
        pool = self.pool
        if len(miss):
            name = np.where(short[miss], h[miss], np.arange(len(miss), dtype=np.uint64))  # long pieces are each their own
            _, first, again = np.unique(name, return_index=True, return_inverse=True)
            one = miss[first]
            new, begin = self.encode([raw[i:j].decode() for i, j in zip(s[one].tolist(), e[one].tolist())])
            size = np.diff(begin)
            begin = begin[:-1] + len(pool)
            pool = np.concatenate((pool, new))
            start[miss], count[miss] = begin[again], size[again]
            kept = np.flatnonzero(short[one] & (self.start[slot[one]] < 0))
            place, k = np.unique(slot[one[kept]], return_index=True)
            if len(place):
                kept = kept[k]
                self.key[place], self.count[place] = h[one[kept]], size[kept]
                ends = np.cumsum(size[kept])
                self.start[place] = len(self.pool) + ends - size[kept]
                self.pool = np.concatenate((self.pool, pool[runs(begin[kept], size[kept])]))
        return pool[runs(start, count)], np.concatenate(([0], np.cumsum(count)))[at]


def runs(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """The places start, start + 1, ... of each run, one after another."""
    return np.repeat(start - np.cumsum(count) + count, count) + np.arange(int(count.sum()))


@lru_cache(4)
def memo(path: str) -> Memo:
    return Memo(path)


class WordBpe:
    """Ids of the word vocabulary as little-endian unsigned 16-bit bytes (32-bit, if the vocabulary needs it)."""

    def __init__(self, path: str):
        self.path = path

    def dtype(self) -> np.dtype:
        return np.dtype("<u2" if library(self.path).get_vocab_size() <= 1 << 16 else "<u4")

    def encode(self, texts: list[str]) -> list[bytes]:
        kind, known = self.dtype(), _splitter(self.path) is not None
        fast = [known and plain(x) for x in texts]
        if any(fast):
            ids, at = memo(self.path).texts([x for x, f in zip(texts, fast) if f])
            raw, at = ids.astype(kind).tobytes(), (at * kind.itemsize).tolist()
            blobs = iter([raw[i:j] for i, j in zip(at, at[1:])])
        return [next(blobs) if f else np.array(library(self.path).encode(x, add_special_tokens=False).ids, kind).tobytes() for f, x in zip(fast, texts)]


def slices_of(column, most: int = 1 << 20, rows: int = 64):
    """(first row, texts) of an Arrow column in runs of about `most` characters, taken a few rows at a time; a null text is empty."""
    out: list[str] = []
    at = n = 0
    for i in range(0, len(column), rows):
        for x in column.slice(i, rows).to_pylist():
            out.append(x or "")
            n += len(out[-1])
        if n >= most:
            yield at, out
            at, out, n = at + len(out), [], 0
    if out:
        yield at, out
