"""BPE encoding and decoding with forced boundaries.

Two symbols that stand side by side inside no vocabulary token can never be merged across, so
every such pair marks a certain cut.  A pre-token is split at its certain cuts, each fragment is
merged by itself (by merge rank, leftmost first) and the ids are concatenated; the result is the
same as merging the whole.  Pieces of text between white space are encoded once per task and
kept in a table of bounded size.

Reads tokenizer files of the library's JSON form whose model is BPE with byte-level symbols:
normalisers NFC, white-space replacement and lower case; splitting by a pattern that drops white
space.  The file's path is a parameter; every executor reads it there (it ships with the
installation), the text of the file is not sent.  Null text counts as empty: no ids, empty
decoded text.
"""

from __future__ import annotations

import json
import unicodedata
from collections.abc import Callable, Iterator
from operator import itemgetter

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks

CACHE_ENTRIES = 200_000
CHUNK_BYTES = 1 << 20
#: Unicode's White_Space property, as the pattern's \s means it.
WHITE_SPACE = "".join(map(chr, (*range(0x09, 0x0E), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)))
_SPLIT = regex.compile(f"[{WHITE_SPACE}]+")
_ODD_SPACE = regex.compile(r"[\x1c-\x1f]")  # str.split() takes these for white space, the pattern doesn't


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    table, extra = {}, 0
    for b in range(256):
        if b in plain:
            table[b] = chr(b)
        else:
            table[b] = chr(256 + extra)
            extra += 1
    return [table[b] for b in range(256)]


Piece = tuple[int, str, str]
_COUNT, _IDS, _NAMES = itemgetter(0), itemgetter(1), itemgetter(2)


def _joined(parts: list[Piece]) -> Piece:
    if len(parts) == 1:
        return parts[0]
    parts = [p for p in parts if p[0]]
    return sum(map(_COUNT, parts)), " ".join(map(_IDS, parts)), " ".join(map(_NAMES, parts))


class Recent(dict):
    """Table that makes what it lacks; of at most twice `size` entries, as the older half goes when
    the younger is full.  Long keys are made anew each time.
    """

    def __init__(self, size: int, make: Callable[[str], Piece], longest: int = 48) -> None:
        super().__init__()
        self.size, self.make, self.longest = size, make, longest
        self.old: dict[str, Piece] = {}

    def __missing__(self, key: str) -> Piece:
        got = self.old.get(key)
        if got is None:
            got = self.make(key)
        if len(key) <= self.longest:
            if len(self) >= self.size:
                self.old = dict(self)
                self.clear()
            self[key] = got
        return got


class Codec:
    """Encoder and decoder of one tokenizer file."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self._check(spec, model)
        self.vocab: dict[str, int] = model["vocab"]
        self.suffix: str = model.get("end_of_word_suffix") or ""
        self.ranks = {}
        for rank, pair in enumerate(model["merges"]):
            self.ranks[tuple(pair) if isinstance(pair, list) else tuple(pair.split(" "))] = rank
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.names = {i: t for t, i in self.vocab.items()} | {i: t for t, i in self.special.items()}
        self.pattern = regex.compile(spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"])
        self.apart = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.symbols = byte_symbols()
        self.inside = self._pairs_inside()
        self._chunks, self._words = Recent(CACHE_ENTRIES, self._piece), Recent(CACHE_ENTRIES, self._word)
        self._parts: dict[str, Piece] = {}

    @staticmethod
    def _check(spec: dict, model: dict) -> None:
        kinds = [n["type"] for n in (spec["normalizer"] or {}).get("normalizers", [])]
        steps = [p["type"] for p in spec["pre_tokenizer"].get("pretokenizers", [])]
        if model["type"] != "BPE" or model.get("continuing_subword_prefix") or kinds != ["NFC", "Replace", "Lowercase"] or steps != ["Split", "ByteLevel"] or spec.get("decoder") or any(t["lstrip"] or t["rstrip"] or t["single_word"] or t["normalized"] for t in spec["added_tokens"]):
            raise ValueError("this form of tokenizer file isn't supported")

    def _pairs_inside(self) -> frozenset[tuple[str, str]]:
        """Neighbouring symbols within some vocabulary token; all other pairs are certain cuts."""
        found = set()
        for token in self.vocab:
            own = self.spell(token)
            found.update(zip(own, own[1:], strict=False))
        return frozenset(found)

    def spell(self, token: str) -> list[str]:
        """Single symbols of a token or word; the last carries the word-end mark."""
        if self.suffix and token.endswith(self.suffix) and len(token) > len(self.suffix):
            body = list(token[: -len(self.suffix)])
            return [*body[:-1], body[-1] + self.suffix]
        return list(token)

    def fragments(self, word: str) -> list[list[str]]:
        """Symbols of a byte-level word, split at every certain cut."""
        own = self.spell(word + self.suffix)
        inside = self.inside
        cuts = [i for i, p in enumerate(zip(own, own[1:], strict=False), 1) if p not in inside]
        if not cuts:
            return [own]
        return [own[i:j] for i, j in zip([0, *cuts], [*cuts, len(own)], strict=True)]

    def merge(self, own: list[str]) -> list[str]:
        """Tokens of one fragment: the best-ranked pair, leftmost first, is joined until none is left."""
        rank, none = self.ranks.get, 1 << 60
        scores = [rank(p, none) for p in zip(own, own[1:], strict=False)]
        while scores:
            best = min(scores)
            if best == none:
                break
            i = scores.index(best)
            own[i : i + 2] = [own[i] + own[i + 1]]
            del scores[i]
            if i:
                scores[i - 1] = rank((own[i - 1], own[i]), none)
            if i < len(scores):
                scores[i] = rank((own[i], own[i + 1]), none)
        return own

    def _fragment(self, own: list[str]) -> Piece:
        tokens = [t for t in self.merge(own) if t in self.vocab]  # others have no id, as in the library
        return len(tokens), " ".join([str(self.vocab[t]) for t in tokens]), " ".join(tokens)

    def _word(self, word: str) -> Piece:
        """A pre-token (normalised text): its fragments, joined."""
        spelled = "".join(map(self.symbols.__getitem__, word.encode("utf-8")))
        parts, known = [], self._parts
        for own in self.fragments(spelled):
            name = "".join(own)
            part = known.get(name)
            if part is None:
                part = self._fragment(own)
                if len(name) <= 48:
                    if len(known) >= CACHE_ENTRIES // 2:
                        known.clear()
                    known[name] = part
            parts.append(part)
        return _joined(parts)

    def normal(self, text: str) -> str:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text)
            return "".join([c.lower() for c in text]) if "Σ" in text else text.lower()  # no final-sigma rule
        return text.lower()

    def _piece(self, chunk: str) -> Piece:
        own = self.normal(chunk)
        if own.isalpha() and max(own) < "\u0250":  # letters only: one pre-token
            return self._words[own]
        return _joined([self._words[w] for w in self.pattern.findall(own)])

    def pieces(self, text: str) -> list[Piece]:
        """(number of ids, ids, decoded text) of each stretch without white space."""
        if self.apart is not None and any(s in text for s in self.special):
            out = []
            for part in self.apart.split(text):
                if part in self.special:
                    out.append((1, str(self.special[part]), part))
                elif part:
                    out.extend(self.pieces(part))
            return out
        odd = _ODD_SPACE.search(text) is not None
        chunks = _SPLIT.split(text) if odd else text.split()
        out = list(map(self._chunks.__getitem__, chunks))
        return [p for p in out if p[0]] if odd else out

    def encode(self, text: str | None) -> list[int]:
        return [int(i) for _, ids, _ in self.pieces(text or "") for i in ids.split(" ")]

    def decode(self, ids: list[int]) -> str:
        """As a tokenizer without a decoder does: token names joined by spaces."""
        return " ".join([self.names[i] for i in ids])


_CODECS: dict[str, Codec] = {}


def codec(path: str) -> Codec:
    if path not in _CODECS:
        _CODECS[path] = Codec(path)
    return _CODECS[path]


def encode_decode(docs: DataFrame, path: str, column: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids (decimal, joined by one space) and decoded text of each document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path)
        for b in batches:
            for part in chunks(b.column(1), CHUNK_BYTES):  # ids and names take several times the text's bytes
                n, ids, decoded = [], [], []
                for text in b.column(1).slice(part.start, part.stop - part.start).to_pylist():
                    pieces = own.pieces(text or "")
                    n.append(sum(map(_COUNT, pieces)))
                    ids.append(" ".join(map(_IDS, pieces)))
                    decoded.append(" ".join(map(_NAMES, pieces)))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(part.start, len(n)), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(decoded, pa.string())], names=["doc_id", "n_tokens", "ids", "decoded"])
        pa.default_memory_pool().release_unused()

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", F.col(column).alias("text")).mapInArrow(run, f"doc_id {kind}, n_tokens long, ids string, decoded string")
