"""Language of mixed text: scripts narrow the candidates, Viterbi labels spans of words.

Training counts, over every training row, the letters' scripts and the hashed 1- to 4-letter
grams of words by language; the model has a fixed size (languages x `BUCKETS`).  A word's score
for a language is the mean log-probability of its grams, scaled by the square root of their
number.  Languages that hardly use the script of the word's first letter are ruled out for it.
A document's words are labelled by the best path under a fixed penalty for each switch.  Where
no stretch of words gains more than one switch costs, the best path is constant and is taken
without a search; this is exact.

The prediction is the language of most words on the path (ties: first by name); the score is the
share of words so labelled.  Null text, and text without letters, gets `und` and 0.  With no
labelled row every document gets `und`.  lang, source and doc_id are never used to predict.
"""

from __future__ import annotations

import re
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator
from functools import cache
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BUCKETS = 1 << 14
SWITCH_PENALTY = 6.0
FLOOR = -30.0
CACHE_ENTRIES = 200_000
PACK = 200
#: First code point of ranges of letters, with their script.
SCRIPTS = ((0x0000, "latin"), (0x0370, "greek"), (0x0400, "cyrillic"), (0x0530, "armenian"), (0x0590, "hebrew"), (0x0600, "arabic"), (0x0900, "indic"), (0x0E00, "southeast"), (0x10A0, "georgian"), (0x1100, "hangul"), (0x1200, "other"), (0x1E00, "latin"), (0x1F00, "greek"), (0x2000, "other"), (0x3040, "kana"), (0x3100, "han"), (0xAC00, "hangul"), (0xD7B0, "other"), (0xF900, "han"), (0xFB00, "other"), (0x20000, "han"), (0x30000, "other"))
_STARTS = [a for a, _ in SCRIPTS]
LONGEST_WORD = 40
LAST_LATIN = "\u036f"


@cache
def script_of(char: str) -> str:
    return SCRIPTS[bisect_right(_STARTS, ord(char)) - 1][1]


@cache
def _words_in() -> re.Pattern:
    """Runs of up to LONGEST_WORD letters; signs for numbers such as a half are none."""
    signs = [c for c in map(chr, range(0x110000)) if c.isnumeric() and not c.isdecimal() and not c.isalpha()]
    ranges, start = [], None
    for a, b in zip(signs, [*signs[1:], None], strict=True):
        start = start or a
        if b is None or ord(b) != ord(a) + 1:
            ranges.append(f"{start}-{a}")
            start = None
    return re.compile(rf"[^\W\d_{''.join(ranges)}]{{1,{LONGEST_WORD}}}")


def words_of(text: str | None) -> list[str]:
    """Words of letters, lower-cased.

    Longer runs, as of scripts without spaces, are consecutive words of LONGEST_WORD letters, and a
    run goes on as a new word where its script changes, so every letter is scored by its script.
    """
    if not text:
        return []
    found = _words_in().findall(text.lower())
    if max(text) <= LAST_LATIN:
        return found
    return [part for w in found for part in ((w,) if max(w) <= LAST_LATIN else ("".join(g) for _, g in groupby(w, script_of)))]


def grams_of(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of the words' 1- to 4-letter grams, ends marked, and the word of each."""
    own = [f"<{w}>" for w in words]
    data = np.frombuffer("".join(own).encode("utf-32-le"), dtype=np.uint32).astype(np.uint64)
    size = np.array([len(w) for w in own], dtype=np.int64)
    word = np.repeat(np.arange(len(own)), size)
    left = np.repeat(np.cumsum(size), size) - np.arange(len(data))  # letters to the word's end
    h, buckets, words_of_grams = np.zeros(len(data), dtype=np.uint64), [], []
    for n in range(1, 5):
        m = len(data) - n + 1
        if m <= 0:
            break
        h = h[:m] * np.uint64(0x9E3779B97F4A7C15) + data[n - 1 :]
        fits = left[:m] >= n
        if n == 1:  # the marks alone say nothing
            fits &= (data != ord("<")) & (data != ord(">"))
        mixed = (h[fits] ^ (h[fits] >> np.uint64(29))) * np.uint64(0xD6E8FEB86659FD93 + 2 * n)
        buckets.append((mixed >> np.uint64(40)).astype(np.int64) % BUCKETS)
        words_of_grams.append(word[:m][fits])
    if not buckets:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(buckets), np.concatenate(words_of_grams)


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Gram and script counts of a partition by language."""
    words: dict[str, Counter] = {}
    grams: dict[str, np.ndarray] = {}
    scripts: Counter = Counter()

    def settle() -> None:
        for lang, own in words.items():
            into = grams.setdefault(lang, np.zeros(BUCKETS, dtype=np.int64))
            seen, times = list(own), np.array(list(own.values()), dtype=np.float64)
            gram, word = grams_of(seen)
            into += np.bincount(gram, times[word], BUCKETS).astype(np.int64) if len(gram) else 0
            for w, c in own.items():
                scripts[lang, script_of(w[0])] += c
            own.clear()

    for b in batches:
        for text, lang in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            words.setdefault(lang, Counter()).update(words_of(text))
            if len(words[lang]) > 100_000:
                settle()
    settle()
    rows = [(lang, "", int(g), int(v[g])) for lang, v in grams.items() for g in np.flatnonzero(v)]
    rows += [(lang, script, -1, c) for (lang, script), c in scripts.items()]
    yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.string(), pa.string(), pa.int32(), pa.int64()))], names=["lang", "script", "gram", "n"])


class LanguageModel:
    """Gram log-probabilities and the languages of each script."""

    def __init__(self, rows: list[tuple]) -> None:
        self.langs = sorted({r[0] for r in rows})
        at = {lang: i for i, lang in enumerate(self.langs)}
        counts = np.full((len(self.langs), BUCKETS), 0.5)
        script: dict[str, np.ndarray] = {}
        for lang, name, gram, n in rows:
            if gram >= 0:
                counts[at[lang], gram] += n
            else:
                script.setdefault(name, np.zeros(len(self.langs)))[at[lang]] += n
        self.logs = np.log(counts / counts.sum(axis=1, keepdims=True)).astype(np.float32)
        total = sum(script.values()) if script else np.ones(len(self.langs))
        self.allowed = {name: v / np.maximum(total, 1) >= 0.001 for name, v in script.items()}
        self._scores: dict[str, int] = {}
        self._table = np.zeros((CACHE_ENTRIES, len(self.langs)), dtype=np.float32)

    def word_scores(self, words: list[str]) -> np.ndarray:
        """A row for each word: its score by language, the best at 0."""
        gram, word = grams_of(words)
        n = np.maximum(np.bincount(word, minlength=len(words)), 1)
        s = np.stack([np.bincount(word, row[gram], len(words)) for row in self.logs], axis=1) / np.sqrt(n)[:, None]
        scripts = [script_of(w[0]) for w in words]
        for name in set(scripts):
            of = np.array([x == name for x in scripts])
            allowed = self.allowed.get(name)
            if allowed is None:
                s[of] = 0.0  # a script never seen tells nothing
            elif allowed.any() and not allowed.all():
                s[np.ix_(of, ~allowed)] = s[of][:, allowed].max(axis=1, keepdims=True) + FLOOR
        return (s - s.max(axis=1, keepdims=True)).astype(np.float32)

    def scores(self, words: list[str]) -> np.ndarray:
        got = list(map(self._scores.get, words))
        if None in got:
            fresh = list({w for w, g in zip(words, got, strict=True) if g is None})
            if len(self._scores) + len(fresh) > CACHE_ENTRIES:
                self._scores.clear()
                fresh = list(set(words))
            if len(fresh) > CACHE_ENTRIES:
                return self.word_scores(words)
            at = len(self._scores)
            self._table[at : at + len(fresh)] = self.word_scores(fresh)
            self._scores.update(zip(fresh, range(at, at + len(fresh)), strict=True))
            got = list(map(self._scores.__getitem__, words))
        return self._table[got]

    def path(self, words: list[str], penalty: float = SWITCH_PENALTY) -> np.ndarray:
        """Index of the language of each word on the best path."""
        return self.path_of(self.scores(words), penalty)

    def path_of(self, scores: np.ndarray, penalty: float = SWITCH_PENALTY) -> np.ndarray:
        s = scores.astype(np.float64)
        best = int(np.argmax(s.sum(axis=0)))
        if len(self.langs) == 1:
            return np.zeros(len(s), dtype=np.int8)
        other = s.copy()
        other[:, best] = -np.inf
        gain = np.concatenate([[0.0], np.cumsum(other.max(axis=1) - s[:, best])])
        if (gain - np.minimum.accumulate(gain)).max() <= penalty:
            return np.full(len(s), best, dtype=np.int8)
        return self._search(s, penalty)

    @staticmethod
    def _search(s: np.ndarray, penalty: float) -> np.ndarray:
        n, k = s.shape
        origin = np.empty((n, k), dtype=np.int8)
        value, own = [0.0] * k, list(range(k))
        for t, row in enumerate(s.tolist()):
            top = max(own, key=value.__getitem__)
            jump = value[top] - penalty
            came = [i if value[i] >= jump else top for i in own]
            value = [(value[i] if value[i] >= jump else jump) + row[i] for i in own]
            origin[t] = came
        out = np.empty(n, dtype=np.int8)
        at = max(own, key=value.__getitem__)
        for t in range(n - 1, -1, -1):
            out[t] = at
            at = origin[t, at]
        return out

    def predict(self, text: str | None) -> tuple[str, float, list[dict]]:
        """Language, share of words and the spans of words of one language."""
        return self.predict_all([text])[0]

    def predict_all(self, texts: list[str | None]) -> list[tuple[str, float, list[dict]]]:
        """Many texts at once: new words are scored together."""
        words = [words_of(t) for t in texts]
        if not self.langs:
            return [("und", 0.0, [])] * len(texts)
        scores = self.scores([w for own in words for w in own])
        out, at = [], 0
        for own in words:
            if not own:
                out.append(("und", 0.0, []))
                continue
            path = self.path_of(scores[at : at + len(own)])
            at += len(own)
            count = np.bincount(path, minlength=len(self.langs))
            cuts = [0, *(np.flatnonzero(path[1:] != path[:-1]) + 1).tolist(), len(own)]
            spans = [{"lang": self.langs[path[a]], "first_word": a, "words": b - a} for a, b in zip(cuts, cuts[1:], strict=False)]
            out.append((self.langs[int(np.argmax(count))], float(count.max() / len(own)), spans))
        return out


def train(labelled: DataFrame) -> LanguageModel:
    """Model from all rows with text and lang; what reaches the driver has a fixed size."""
    own = labelled.where("text is not null and lang is not null").select("text", F.col("lang").cast("string").alias("lang"))
    counts = own.mapInArrow(_count, "lang string, script string, gram int, n long")
    rows = counts.groupBy("lang", "script", "gram").agg(F.sum("n").alias("n")).collect()
    return LanguageModel([tuple(r) for r in rows])


def identify(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """doc_id, lang_pred, score and spans for every document."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = sent.value
        span = pa.list_(pa.struct([("lang", pa.string()), ("first_word", pa.int64()), ("words", pa.int64())]))
        for b in batches:
            texts = b.column(1).to_pylist()
            got = [p for i in range(0, len(texts), PACK) for p in own.predict_all(texts[i : i + PACK])]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64()), pa.array([g[2] for g in got], span)], names=["doc_id", "lang_pred", "score", "spans"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, lang_pred string, score double, spans array<struct<lang:string,first_word:long,words:long>>")


def held_out(docs: DataFrame) -> DataFrame:
    """Adds held_out: the crc32 of doc_id as text, modulo 5, is 0."""
    return docs.withColumn("held_out", F.coalesce(F.pmod(F.crc32(F.encode(F.col("doc_id").cast("string"), "UTF-8")), F.lit(5)) == 0, F.lit(False)))
