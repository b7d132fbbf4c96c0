"""Language identification with spans.

Training counts hashed character n-grams (1 to 4, with word bounds) of words by language, over at most `TRAIN` labelled documents (chosen by a
hash of their id), and which scripts each language uses. A word's script, from Unicode ranges, narrows the languages that may
have it; each of these gets the mean log likelihood of its n-grams, weighted by the word's length up to a bound. Over a text's words, Viterbi finds the sequence of languages
with the largest sum of scores less a penalty for each switch; runs of a language are the spans. A document's language is that of most letters.

Most texts have one language, and a bound shows it: if no run of words prefers another language to the best one by more than half a
penalty, no switch can pay, and the best constant path is the optimum. Only the others go through the recursion.

A word of a script that no learned language uses says nothing of languages; its letters count against the score. `learned` is the share of a
text's letters that are in words of the other scripts: 1 for a mixture of learned languages, however small the share of each.

Null or empty texts, and texts without any letter, are `und` with score 0. Words without letters carry no score. If there is nothing to
learn from, all texts are `und`.
"""

from __future__ import annotations

import bisect
import unicodedata
from collections import Counter

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, functions as F

from . import common as C, tokens as T

TRAIN, BUCKETS, SWITCH, MEMO = 20_000, 1 << 16, 40.0, 200_000
#: First code points of script ranges (fixed values of Unicode's blocks), with a name for each.
SCRIPTS = (
    (0x0000, "latin"), (0x0370, "greek"), (0x0400, "cyrillic"), (0x0530, "armenian"), (0x0590, "hebrew"), (0x0600, "arabic"), (0x0700, "other"), (0x0750, "arabic"), (0x0780, "other"),
    (0x08A0, "arabic"), (0x0900, "devanagari"), (0x0980, "bengali"), (0x0A00, "gurmukhi"), (0x0A80, "gujarati"), (0x0B00, "other"), (0x0B80, "tamil"), (0x0C00, "telugu"), (0x0C80, "kannada"),
    (0x0D00, "malayalam"), (0x0D80, "other"), (0x0E00, "thai"), (0x0E80, "lao"), (0x0F00, "other"), (0x10A0, "georgian"), (0x1100, "hangul"), (0x1200, "ethiopic"), (0x13A0, "other"),
    (0x1E00, "latin"), (0x1F00, "greek"), (0x2000, "other"), (0x2C60, "latin"), (0x2C80, "other"), (0x2E80, "han"), (0x3040, "kana"), (0x3100, "han"), (0x3130, "hangul"), (0x31C0, "han"),
    (0x4DC0, "other"), (0x4E00, "han"), (0xA000, "other"), (0xA720, "latin"), (0xA800, "other"), (0xAC00, "hangul"), (0xD800, "other"), (0xF900, "han"), (0xFB00, "latin"), (0xFB1D, "hebrew"),
    (0xFB50, "arabic"), (0xFE00, "other"), (0xFF66, "kana"), (0xFFA0, "other"), (0x20000, "han"), (0x32000, "other"),
)
_STARTS = [s for s, _ in SCRIPTS]


def script(word: str) -> str:
    """The script of most of a word's letters."""
    if word.isascii() or max(word) < "\u0370":
        return "latin" if any(map(str.isalpha, word)) else ""
    n = Counter(SCRIPTS[bisect.bisect_right(_STARTS, ord(c)) - 1][1] for c in word if c.isalpha())
    return min(n, key=lambda s: (-n[s], s)) if n else ""


_NO_LETTER = {i: None for i in range(128) if not chr(i).isalpha()}
_MARKED = regex.compile(r"[^\p{L}\p{M}]+")


def letters(word: str) -> str:
    """A word as it is scored: its letters and marks, composed and in lower case."""
    if word.isascii():
        return word.lower() if word.isalpha() else word.translate(_NO_LETTER).lower()
    return _MARKED.sub("", unicodedata.normalize("NFC", word.lower()))


def grams(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of the n-grams of non-empty words, with their bounds marked, all words together; and the word of each n-gram."""
    cp = np.frombuffer("".join([f"<{w}>" for w in words]).encode("utf-32-le"), "<u4").astype(np.uint64)
    size = np.fromiter(map(len, words), np.int64, len(words)) + 2
    word = np.repeat(np.arange(len(words)), size)
    left = np.repeat(np.cumsum(size), size) - np.arange(len(cp))  # characters from here to the word's end
    h, buckets, owners = np.zeros(len(cp), np.uint64), [], []
    for n in range(1, 5):
        h = h * C._M3 + np.concatenate((cp[n - 1 :], np.zeros(min(n - 1, len(cp)), np.uint64)))[: len(cp)] + np.uint64(n)
        ok = left >= n
        buckets.append((C.mix(h[ok], 60 + n) & np.uint64(BUCKETS - 1)).astype(np.int64))
        owners.append(word[ok])
    return np.concatenate(buckets), np.concatenate(owners)


class Model:
    """`logp`: log probability of an n-gram by bucket and language; `scripts`: languages that may have a script."""

    def __init__(self, langs: list[str], counts: np.ndarray, scripts: dict[str, list[int]]):
        self.langs = langs
        c = counts + 0.1
        self.logp = np.log(c / c.sum(0)).astype(np.float64)
        if langs:
            self.logp -= self.logp.mean(1, keepdims=True)
        self.scripts = scripts
        self._forget()

    @property
    def narrow(self) -> bool:
        """Whether any script is not shared by all languages; if all are, a word's script decides nothing."""
        return any(len(v) < len(self.langs) for v in self.scripts.values())

    def _forget(self) -> None:
        self.memo: dict[str, int] = {}
        self.rows = np.zeros((1024, len(self.langs)))
        self.sizes = np.zeros(1024, np.int64)
        self.known = np.zeros(1024, bool)

    def _learn(self, words: list[str]) -> None:
        """Scores new words, all together."""
        clean = list(map(letters, words))
        at = [i for i, w in enumerate(clean) if w]
        first, need = len(self.memo), len(self.memo) + len(words)
        while need > len(self.rows):
            self.rows, self.sizes, self.known = (np.concatenate((x, x)) for x in (self.rows, self.sizes, self.known))
        self.rows[first:need], self.sizes[first:need], self.known[first:need] = 0, 0, True
        if at:
            some = [clean[i] for i in at]
            bucket, owner = grams(some)
            size = np.fromiter(map(len, some), np.int64, len(some))
            n = np.bincount(owner, minlength=len(some))
            s = np.stack([np.bincount(owner, weights=self.logp[bucket, g], minlength=len(some)) for g in range(len(self.langs))], 1)
            s *= (np.minimum(size, 12) / n)[:, None]
            for i, w in enumerate(some):
                if not self.narrow and w < "\u0250":  # Latin letters first, and all languages share what scripts there are
                    continue
                may = self.scripts.get(script(w))
                self.known[first + at[i]] = may is not None
                if may is not None and len(may) < len(self.langs):
                    s[i] = np.where(np.isin(np.arange(len(self.langs)), may), s[i], s[i].min() - SWITCH)
            self.rows[first + np.array(at)] = s
            self.sizes[first + np.array(at)] = size
        for i, w in enumerate(words):
            self.memo[w] = first + i

    def ready(self, texts: list[str]) -> list[list[str]]:
        """Words of texts, all of them known to the memo."""
        split = [t.split() for t in texts]
        if len(self.memo) > MEMO:
            self._forget()
        new = {w for ws in split for w in ws if w not in self.memo}
        if new:
            self._learn(list(new))
        return split

    def scores(self, words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Scores (words, languages), letters, and those of learned scripts, of each word that `ready` has seen."""
        at = np.fromiter(map(self.memo.__getitem__, words), np.int64, len(words))
        n = self.sizes[at]
        return self.rows[at], n, n * self.known[at]

    def path(self, s: np.ndarray) -> np.ndarray | None:
        """The best sequence of languages for the words' scores; None, if it is one language throughout."""
        best = int(s.sum(0).argmax())
        c = np.vstack([np.zeros(s.shape[1]), np.cumsum(s - s[:, [best]], 0)])
        if (c - np.minimum.accumulate(c, 0)).max() <= SWITCH / 2:
            return None
        rows = s.tolist()
        v, back = rows[0], []
        for r in rows[1:]:
            top = max(v)
            at, cut = v.index(top), top - SWITCH
            back.append([at if cut > x else i for i, x in enumerate(v)])
            v = [(cut if cut > x else x) + y for x, y in zip(v, r)]
        out = [v.index(max(v))]
        for b in reversed(back):
            out.append(b[out[-1]])
        return np.array(out[::-1])

    def label(self, text: str | None) -> tuple[str, float, list[tuple[int, int, str]]]:
        """Language, score (the share of letters it has, 0 to 1; letters of scripts that no learned language uses are nobody's) and spans (first word, end, language) of a whole text."""
        return self.labels([text or ""])[0]

    def labels(self, texts: list[str]) -> list[tuple[str, float, list[tuple[int, int, str]]]]:
        return [f[:3] for f in self.judged(texts)]

    def judged(self, texts: list[str]) -> list[tuple[str, float, list[tuple[int, int, str]], float]]:
        """Labels of texts, with the share of letters in words of learned scripts."""
        if not self.langs:
            return [("und", 0.0, [], 0.0)] * len(texts)
        return [self._judge(ws) for ws in self.ready(texts)]

    def _judge(self, ws: list[str]) -> tuple[str, float, list[tuple[int, int, str]], float]:
        if not ws:
            return "und", 0.0, [], 0.0
        s, n, own = self.scores(ws)
        if not n.any():
            return "und", 0.0, [], 0.0
        learned = float(own.sum() / n.sum())
        p = self.path(s)
        if p is None:
            best = int(s.sum(0).argmax())
            return self.langs[best], learned, [(0, len(ws), self.langs[best])], learned
        share = np.bincount(p, weights=own, minlength=len(self.langs))
        best = int(share.argmax())
        at = np.flatnonzero(np.diff(p)) + 1
        spans = [(int(a), int(b), self.langs[p[a]]) for a, b in zip([0, *at], [*at, len(p)])]
        return self.langs[best], float(share[best] / n.sum()), spans, learned


def train(labelled: DataFrame, limit: int = TRAIN) -> Model:
    """A model from (doc_id, text, lang) rows; at most `limit` of them, chosen by hash. Counts of fixed size reach the driver."""
    C.ship(labelled.sparkSession)
    rows = C.hashed_sample(labelled.where("text is not null and lang is not null"), ["doc_id"], limit).select("text", "lang")

    def count(batches):
        grams_of: dict[str, np.ndarray] = {}
        scripts: Counter = Counter()
        for x in C.freed(batches):
            for text, lang in zip(x.column(0).to_pylist(), x.column(1).to_pylist()):
                c = grams_of.setdefault(lang, np.zeros(BUCKETS, np.int64))
                words = Counter(map(letters, text.split()))
                words.pop("", None)
                if words:
                    bucket, owner = grams(list(words))
                    times = np.fromiter(words.values(), np.int64, len(words))
                    c += np.bincount(bucket, weights=times[owner], minlength=BUCKETS).astype(np.int64)
                for w, n in words.items():
                    scripts[lang, script(w)] += n
        for lang, c in grams_of.items():
            own = {s: n for (g, s), n in scripts.items() if g == lang}
            yield C.batch_of({"lang": pa.array([lang]), "counts": pa.array([c.tobytes()], pa.binary()), "scripts": pa.array([list(own)], pa.list_(pa.string())), "words": pa.array([list(own.values())], pa.list_(pa.int64()))})

    total: dict[str, np.ndarray] = {}
    scripts: Counter = Counter()
    found = rows.repartition(8).mapInArrow(count, "lang string, counts binary, scripts array<string>, words array<long>")
    for r in C.stash(found, "counts").toLocalIterator():  # eight rows a language, counted side by side and read a few at a time
        total[r["lang"]] = total.get(r["lang"], 0) + np.frombuffer(r["counts"], np.int64)
        for s, n in zip(r["scripts"], r["words"]):
            scripts[r["lang"], s] += n
    langs = sorted(total)
    words = {g: sum(n for (x, _), n in scripts.items() if x == g) for g in langs}
    may = {s: [i for i, g in enumerate(langs) if scripts[g, s] > words[g] / 1000] for s in {s for _, s in scripts}}
    return Model(langs, np.stack([total[g] for g in langs], 1) if langs else np.zeros((BUCKETS, 0)), {s: v for s, v in may.items() if v})


def held_out(doc_id: Column) -> Column:
    return F.crc32(F.encode(doc_id.cast("string"), "utf-8")) % 4 == 2


def predict(docs: DataFrame, model: Model, spans: bool = False, learned: bool = False) -> DataFrame:
    """Adds lang_pred and score (and spans, and learned, if asked for) to `docs`, of which only text is used. Columns of these names are replaced."""
    C.ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast((model.langs, model.logp, model.scripts))
    keep = [c for c in docs.columns if c not in ("lang_pred", "score", "spans", *["learned"] * learned)]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema if f.name in keep) + ", lang_pred string, score double" + ", spans array<struct<first: int, end: int, lang: string>>" * spans + ", learned double" * learned

    def run(batches):
        m = Model.__new__(Model)
        m.langs, m.logp, m.scripts = sent.value
        m._forget()
        for x in C.freed(batches):
            found = [f for _, texts in T.slices_of(x.column("text")) for f in m.judged(texts)]
            out = {c: x.column(c) for c in keep} | {"lang_pred": pa.array([f[0] for f in found], pa.string()), "score": pa.array([f[1] for f in found], pa.float64())}
            if spans:
                out["spans"] = pa.array([[{"first": a, "end": b, "lang": g} for a, b, g in f[2]] for f in found], pa.list_(pa.struct([("first", pa.int32()), ("end", pa.int32()), ("lang", pa.string())])))
            if learned:
                out["learned"] = pa.array([f[3] for f in found], pa.float64())
            yield C.batch_of(out)

    return docs.select(*keep).mapInArrow(run, schema)


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every row; learns from the labelled rows that are not held out."""
    docs = docs.select(F.col("doc_id"), F.col("text").cast("string"), F.col("lang").cast("string"))
    out = F.coalesce(held_out(F.col("doc_id")), F.lit(False))
    model = train(docs.where(~out))
    return predict(docs.select("doc_id", "text", out.alias("held_out")), model).select("doc_id", "held_out", "lang_pred", "score")
