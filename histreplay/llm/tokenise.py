"""Whole-text encoding by the tokenizers library, with a cache of the pieces that its pre-tokenizer cuts texts into."""

from __future__ import annotations

import json
import re
from array import array
from collections.abc import Iterator
from functools import lru_cache
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from histreplay.llm.common import ARROW_ROWS, give_back, ship, tidied

#: Pieces that a worker keeps, about 200 bytes each; when there are more, the cache starts anew.
CACHE_PIECES = 1_200_000
#: The same for word_level, whose new words cost little.
CACHE_WORDS = 250_000
#: Words of at most so many bytes are merged here, many at once; longer ones by the library.
WIDE = 32
#: The rank of a pair that is never merged, with a place in the word.
_NONE = np.int32(2**31 - 1)
#: New words that are encoded in one call of the library.
JOINED = 2000
#: Rows of a batch that goes back to Spark.
ROWS = 256
#: The letters, numbers and white space of Latin-1, and by them the two vocabularies' public split patterns.
_L, _N, _S = "A-Za-zªµºÀ-ÖØ-öø-ÿ", "0-9²³¹¼½¾", r"\t-\r \x85\xa0"
_KNOWN = {
    "byte_level": (None, {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": True}),
    "word_level": (
        {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]},
        {"type": "Sequence", "pretokenizers": [{"type": "Split", "pattern": {"Regex": r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"}, "behavior": "Removed", "invert": True}, {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}]},
    ),
}
_SPLIT = {
    "byte_level": re.compile(f"'s|'t|'re|'ve|'m|'ll|'d| ?[{_L}]+| ?[{_N}]+| ?[^{_S}{_L}{_N}]+|[{_S}]+(?![^{_S}])|[{_S}]+"),
    "word_level": re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{_L}]+|[{_N}]|[^{_S}{_L}{_N}]+"),
}

#: What each Latin-1 character is to the split pattern of word_level: white space, letter, number, other.
_KIND = np.array([next((k for k, own in enumerate((_S, _L, _N)) if re.match(f"[{own}]", chr(c))), 3) for c in range(256)], np.uint8)
#: The character that the vocabularies put for a byte: itself if it is printable, else one from 256 on.
_HIDDEN = [b for b in range(256) if not (33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255)]
_SHOWN = {b: chr(256 + k) for k, b in enumerate(_HIDDEN)}


def word_cuts(text: bytes, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of what the split pattern of word_level finds in lower-case Latin-1 texts, text after text; off are the texts' offsets.

    Runs of letters, runs of other characters and single numbers; an apostrophe at which a match begins takes a short
    ending of the pattern's with it, after which a new match begins.
    """
    data = np.frombuffer(text, np.uint8)
    kind = np.append(_KIND[data], np.uint8(0))
    heads = np.zeros(len(kind), bool)
    heads[off] = True
    begin = heads | (kind == 2)
    begin[1:] |= kind[1:] != kind[:-1]
    at = np.flatnonzero(data == 39)
    at = at[begin[at] & (kind[at + 1] == 1) & ~heads[at + 1]]
    one = np.isin(data[at + 1], np.frombuffer(b"stmd", np.uint8))
    late = np.minimum(at + 2, len(data) - 1)
    pair = (data[at + 1].astype(np.int64) << 8 | data[late]) * ((kind[at + 2 - (at + 2 > len(data))] == 1) & (late == at + 2) & ~heads[late])
    two = np.isin(pair, [ord(x) << 8 | ord(y) for x, y in ("re", "ve", "ll")])
    begin[at[one | two] + 1] = False
    after = np.concatenate([at[one] + 2, at[two] + 3])
    begin[after[kind[after] == 1]] = True
    cuts = np.flatnonzero(begin)
    full = kind[cuts[:-1]] > 0
    return cuts[:-1][full], cuts[1:][full]


class Merges:
    """The merges of a BPE model over bytes, done for many words at once; each step merges one pair of each word, as the model does.

    That pair is the word's of lowest rank, the first of such. Ranks are found in a hash table of pairs with linear probing.
    """

    SLOTS = 18

    def __init__(self, vocab: dict[str, int], merges: list[list[str]], suffix: str) -> None:
        shown = [_SHOWN.get(b, chr(b)) for b in range(256)]
        self.base = np.array([vocab[c] for c in shown], np.int32)
        self.last = np.array([vocab[c + suffix] for c in shown], np.int32)
        self.made = np.array([vocab[a + b] for a, b in merges], np.int32)
        ranks = {vocab[a] << 16 | vocab[b]: k for k, (a, b) in enumerate(merges)}
        keys, rank = np.fromiter(ranks, np.uint32, len(ranks)), np.fromiter(ranks.values(), np.int32, len(ranks))
        self.keys, self.ranks = np.full(1 << self.SLOTS, 0xFFFFFFFF, np.uint32), np.full(1 << self.SLOTS, _NONE, np.int32)
        slot = self._slot(keys)
        while len(keys):
            free = self.ranks[slot] == _NONE
            self.keys[slot[free]], self.ranks[slot[free]] = keys[free], rank[free]
            out = self.keys[slot] != keys
            self.ranks[slot[~out]] = rank[~out]
            keys, rank, slot = keys[out], rank[out], (slot[out] + 1) & ((1 << self.SLOTS) - 1)

    @classmethod
    def of(cls, model: dict) -> Merges | None:
        """None where the model isn't one of plain merges, lacks a byte, or is too large for the tables."""
        vocab, merges, suffix = model["vocab"], model.get("merges", []), model.get("end_of_word_suffix") or ""
        plain = model["type"] == "BPE" and not any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "byte_fallback", "ignore_merges"))
        if not plain or max(vocab.values(), default=0) >= 0xFFFF or len(merges) > 1 << cls.SLOTS - 1 or not all(len(m) == 2 and not isinstance(m, str) for m in merges):
            return None
        return cls(vocab, merges, suffix) if all(_SHOWN.get(b, chr(b)) + x in vocab for b in range(256) for x in ("", suffix)) else None

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint32(0x9E3779B1)) >> np.uint32(32 - self.SLOTS)).astype(np.int32)

    def _keyed(self, left: np.ndarray, right: np.ndarray, place: np.ndarray) -> np.ndarray:
        """Rank and place of pairs in one number, by which they are taken; _NONE for those that aren't merged."""
        keys = (left << 16 | right).view(np.uint32)
        slot = self._slot(keys)
        held, rank = self.keys[slot], self.ranks[slot]
        open_ = np.flatnonzero((held != keys) & (rank != _NONE))
        rank[held != keys] = _NONE
        while len(open_):
            slot[open_] = (slot[open_] + 1) & ((1 << self.SLOTS) - 1)
            held, found = self.keys[slot[open_]], self.ranks[slot[open_]]
            same = held == keys[open_]
            rank[open_[same]] = found[same]
            open_ = open_[~same & (found != _NONE)]
        return np.where(rank == _NONE, _NONE, rank * WIDE + place)

    def ids(self, data: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all words, their number for each word) of words of 1 to WIDE bytes; data are the bytes, size those of each."""
        at = np.cumsum(size) - size
        ends = at + size - 1
        sym = self.base[data]
        sym[ends] = self.last[data[ends]]
        place = (np.arange(len(data)) - np.repeat(at, size)).astype(np.int32)
        key = np.full(len(data), _NONE)
        inner = np.ones(len(data), bool)
        inner[ends] = False
        inner = np.flatnonzero(inner)
        key[inner] = self._keyed(sym[inner], sym[inner + 1], place[inner])
        own, n, count, whole = np.arange(len(size)), size, np.zeros(len(size), np.int64), []
        while len(own):
            least = np.minimum.reduceat(key, at)
            if (least == _NONE).any():
                gone = least == _NONE
                count[own[gone]] = n[gone]
                out = np.repeat(gone, n)
                whole.append((own[gone], sym[out]))
                own, n, least = own[~gone], n[~gone], least[~gone]
                sym, key, place = sym[~out], key[~out], place[~out]
                at = np.cumsum(n) - n
                if not len(own):
                    break
            i = np.flatnonzero(key == np.repeat(least, n))
            sym[i], key[i] = self.made[least // WIDE], _NONE
            right = i[i + 2 < at + n]
            key[right] = self._keyed(sym[right], sym[right + 2], place[right])
            left = i[i > at] - 1
            key[left] = self._keyed(sym[left], sym[left + 1], place[left])
            stay = np.ones(len(sym), bool)
            stay[i + 1] = False
            sym, key, place, n = sym[stay], key[stay], place[stay], n - 1
            at = np.cumsum(n) - n
        flat, first = np.zeros(count.sum(), np.uint32), np.cumsum(count) - count
        for words, ids in whole:
            n = count[words]
            flat[np.repeat(first[words] - (np.cumsum(n) - n), n) + np.arange(len(ids))] = ids
        return flat, count


class Encoder:
    """ids of texts as little-endian unsigned 32-bit bytes, equal to the library's encode(text, add_special_tokens=False).

    Both vocabularies merge within pre-tokens only, so a text's ids are those of its pre-tokens one after the other.
    Texts in Latin-1 without a special token's marks are cut here and their pieces encoded by the library once a worker;
    every other text goes to the library whole, and so does any text if the vocabulary file's normaliser and
    pre-tokeniser are not those of _KNOWN, by which the texts are cut.
    """

    def __init__(self, path: str, kind: str, most: int | None = None) -> None:
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.lower = kind == "word_level"
        with open(path, encoding="utf-8") as f:
            own = json.load(f)
        self.split = _SPLIT[kind] if (own["normalizer"], own["pre_tokenizer"]) == _KNOWN[kind] else None
        # byte_level: a piece's ids. word_level: the place of a piece in `first` and `count`, which say where its ids lie in `ids`.
        self.cache: dict[str, bytes] | dict[str, int] = {}
        self.most = (CACHE_WORDS if self.lower else CACHE_PIECES) if most is None else most
        self.merges = Merges.of(own["model"]) if self.lower and self.split is not None else None
        self.forget_words()

    def forget_words(self) -> None:
        self.cache.clear()
        self.ids, self.first, self.count = np.zeros(0, "<u4"), np.zeros(0, np.int32), np.zeros(0, np.int32)

    def _library(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.library.encode_batch_fast(texts, add_special_tokens=False)]

    def _cuttable(self, text: str) -> bool:
        if self.split is None or "<|" in text:
            return False
        if not text.isascii():
            try:
                text.encode("latin-1")
            except UnicodeEncodeError:
                return False
        return True

    def pieces(self, text: str) -> list[str] | None:
        return self.split.findall(text.lower() if self.lower else text) if self._cuttable(text) else None

    def _learn(self, new: list[str]) -> None:
        """Encodes new pieces of byte_level. Plain words go in one text, where the library cuts them apart again as it does in any text."""
        words = [x for x in new if x.startswith(" ") and x[1:].isalpha()]
        rest = set(new).difference(words)
        for k in range(0, len(words), JOINED):
            own = words[k : k + JOINED]
            found = self.library.encode("".join(own), add_special_tokens=False)
            ids = array("I", found.ids).tobytes()
            ends = (4 * (np.flatnonzero(np.diff(np.array(found.word_ids, np.int64))) + 1)).tolist()
            if len(ends) + 1 != len(own):
                rest.update(own)
                continue
            self.cache.update(zip(own, map(ids.__getitem__, map(slice, [0, *ends], [*ends, len(ids)]))))
        left = list(rest)
        self.cache.update(zip(left, self._library(left)))

    def _learn_words(self, new: list[str]) -> None:
        """Encodes new pieces of word_level; they are in Latin-1 and lower case, which the library's other steps leave as it is."""
        text = "".join(new)
        cuts = np.append(0, np.cumsum(np.fromiter(map(len, new), np.int64, len(new))))
        size = np.diff(np.append(0, np.cumsum(1 + (np.frombuffer(text.encode("latin-1"), np.uint8) > 127)))[cuts])
        short = size <= (WIDE if self.merges is not None else 0)
        flat, count = np.zeros(0, np.uint32), np.zeros(len(new), np.int64)
        if short.any():
            data = np.frombuffer(text.encode(), np.uint8)
            flat, count[short] = self.merges.ids(data[np.repeat(short, size)], size[short])
        first = np.cumsum(count) - count
        rest = np.flatnonzero(~short).tolist()
        long_ = [np.frombuffer(x, "<u4") for x in self._library([new[i] for i in rest])] if rest else []
        for i, ids in zip(rest, long_):
            count[i] = len(ids)
        first[rest] = len(flat) + np.cumsum(count[rest]) - count[rest]
        self.cache.update(zip(new, range(len(self.first), len(self.first) + len(new))))
        self.first = np.append(self.first, (first + len(self.ids)).astype(np.int32))
        self.count = np.append(self.count, count.astype(np.int32))
        self.ids = np.concatenate([self.ids, flat, *long_])

    def _known(self, words: list[str]) -> np.ndarray:
        """Places of pieces of word_level, to which those that the cache lacks are added."""
        found = np.fromiter(map(self.cache.get, words, repeat(-1)), np.int64, len(words))
        gaps = np.flatnonzero(found < 0)
        if len(gaps):
            at = len(self.first)
            self._learn_words([words[i] for i in gaps.tolist()])
            found[gaps] = np.arange(at, at + len(gaps))
        return found

    def _encode_words(self, texts: list[str]) -> list[bytes]:
        """ids of Latin-1 texts by word_level: all are cut at once, and there is one look into the cache for each distinct piece."""
        text = "".join(texts).lower().encode("latin-1")
        off = np.append(0, np.cumsum([len(x) for x in texts]))
        start, end = word_cuts(text, off)
        if not len(start):
            return [b""] * len(texts)
        data = np.frombuffer(text, np.uint8)
        ends = np.append(0, np.cumsum(end - start)).astype(np.int32)
        pieces = pa.Array.from_buffers(pa.binary(), len(start), [None, pa.py_buffer(ends), pa.py_buffer(data[_KIND[data] > 0])]).dictionary_encode()
        _, bounds, body = pieces.dictionary.buffers()
        bounds, body = np.frombuffer(bounds, np.int32)[: len(pieces.dictionary) + 1].tolist(), body.to_pybytes().decode("latin-1")
        known = self._known([body[a:b] for a, b in zip(bounds, bounds[1:])])[pieces.indices.to_numpy()]
        first, n = self.first[known], self.count[known]
        total = np.append(0, np.cumsum(n))
        flat = self.ids[np.repeat(first - total[:-1], n) + np.arange(total[-1])]
        edge = total[np.searchsorted(start, off)].tolist()
        return [flat[a:b].tobytes() for a, b in zip(edge, edge[1:])]

    def encode(self, texts: list[str]) -> list[bytes]:
        """One look into the cache for each piece; the places of those it lacks are filled in once they are known."""
        if len(self.cache) > self.most:
            self.forget_words()
        if self.lower and self.split is not None:
            whole = [self._cuttable(x) for x in texts]
            cut = iter(self._encode_words([x for x, own in zip(texts, whole) if own]))
            return [next(cut) if own else self._library([x])[0] for x, own in zip(texts, whole)]
        get, out, open_ = self.cache.get, [], []
        for k, text in enumerate(texts):
            own = self.pieces(text)
            if own is None:
                out.append(self._library([text]))
                continue
            found = list(map(get, own))
            gaps = [i for i, x in enumerate(found) if x is None]
            if gaps:
                open_.append((found, gaps, [own[i] for i in gaps]))
            out.append(found)
        if open_:
            self._learn(list({x for _, _, words in open_ for x in words}))
            for found, gaps, words in open_:
                for i, x in zip(gaps, words):
                    found[i] = self.cache[x]
        return [b"".join(x) for x in out]


@lru_cache(maxsize=4)
def encoder(path: str, kind: str, most: int | None = None) -> Encoder:
    """One for each worker and vocabulary; the library's own threads stay off, since Spark's tasks fill the cores."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    return Encoder(path, kind, most)


def forget() -> None:
    """Frees the worker's encoders with their caches, for tasks that come after the last text is encoded."""
    if encoder.cache_info().currsize:
        encoder.cache_clear()
        give_back()


def encoded(batch: pa.RecordBatch, tok: Encoder, columns: tuple[int, ...], text: int, rows: int = 256, most: int = 1 << 19) -> Iterator[tuple]:
    """(*columns, ids) of each row in order; `rows` rows or about `most` characters of text are in Python at a time."""
    for at in range(0, batch.num_rows, rows):
        part = batch.slice(at, rows)
        rest, texts = [part.column(k).to_pylist() for k in columns], part.column(text)
        held, size, first = [], 0, 0
        for k in range(part.num_rows):
            held.append(texts[k].as_py())
            size += len(held[-1])
            if size >= most or k + 1 == part.num_rows:
                for i, ids in enumerate(tok.encode(held), first):
                    yield (*[c[i] for c in rest], ids)
                held, size, first = [], 0, k + 1


def ids_of(data: bytes, wide: bool) -> np.ndarray:
    return np.frombuffer(data, "<u4" if wide else "<u2")


def tokenised(docs: DataFrame, vocabulary: str, kind: str, end_id: int, id_col: str, text_col: str, cache_pieces: int | None = None) -> DataFrame:
    """(id, n, wide, data): token ids with the end id, as little-endian integers of two bytes, or four where wide.

    Null texts count as empty. Texts are encoded where they are read, so that only ids need be shuffled.
    """
    ship(docs.sparkSession)
    names, kinds = ("id", "n", "wide", "data"), (pa.int64(), pa.int64(), pa.bool_(), pa.binary())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = encoder(vocabulary, kind, cache_pieces)
        runs = (ARROW_ROWS, 1 << 20) if tok.lower else ()
        end = np.array([end_id], "<u4").tobytes()
        out: list[tuple] = []
        for batch in batches:
            for name, data in encoded(batch, tok, (0,), 1, *runs):
                t = np.frombuffer(data + end, "<u4")
                wide = bool(t.max() > 0xFFFF)
                out.append((name, len(t), wide, (t if wide else t.astype("<u2")).tobytes()))
                if len(out) == ROWS:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], list(names))
                    out = []
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], list(names))

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return rows.mapInArrow(tidied(run), "id long, n long, wide boolean, data binary")
