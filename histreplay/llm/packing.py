"""Packing documents into training windows with lexical neighbours, found by BM25 in shards of like documents."""

from __future__ import annotations

import zlib
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from histreplay.llm.common import range_bounds, ship, shuffle_width, stored, tidied
from histreplay.llm.tokenise import CACHE_WORDS, forget, ids_of, tokenised


#: Rows of a batch that goes back to Spark.
PIECES = 256
#: A term that one in so many documents of a shard holds has its weights in a row for all of them.
DENSE = 8
#: Neighbours that are put in order at first; the others only if these don't fill a window.
FEW = 64
#: Token ids whose terms are counted at once.
RUN_IDS = 1 << 18
#: Text of a task's shards, about, once there are more of them than the session's shuffle partitions.
TASK_BYTES = 256 << 20


@dataclass(frozen=True)
class PackSpec:
    """window: tokens of a sequence; shard_bytes: text that shares an index, about; terms: of a query, the weightiest, or None for all;

    cache_pieces: what a Python worker keeps of encoded pieces until the texts are encoded.
    """

    window: int = 4096
    end_id: int = 2
    shard_bytes: int = 8 << 20
    terms: int | None = None
    k1: float = 1.2
    b: float = 0.75
    cache_pieces: int = CACHE_WORDS


@dataclass(frozen=True)
class Corpus:
    """What BM25 takes from all documents: their number, mean length in tokens, and how many of them hold each token id."""

    n: int
    mean: float
    df: np.ndarray


def counted(tokens: Sequence[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, token id, count) of each id that a document holds, ordered by document and id; documents aren't empty.

    Keys of half the width serve ids of two bytes in few documents.
    """
    ids = np.concatenate(tokens)
    bits, kind = (16, np.uint32) if ids.dtype.itemsize == 2 and len(tokens) <= 1 << 16 else (32, np.uint64)
    keys = np.repeat(np.arange(len(tokens), dtype=kind) << kind(bits), [len(t) for t in tokens])
    keys |= ids
    keys.sort()
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    count = np.diff(np.append(first, len(keys)))
    keys = keys[first]
    return (keys >> kind(bits)).astype(np.int32), (keys & kind((1 << bits) - 1)).astype(np.uint32), count


class Index:
    """A BM25 index over the token ids of one shard's documents, with the statistics of the corpus, or else the shard's own."""

    def __init__(self, tokens: list[np.ndarray], spec: PackSpec, corpus: Corpus | None = None) -> None:
        self.n, self.terms = len(tokens), spec.terms
        lens = np.array([len(t) for t in tokens], np.int64)
        doc, term, tf = counted(tokens)
        tf = tf.astype(np.float32)
        held = np.bincount(term)
        ids = np.flatnonzero(held)
        held[ids], self.held = np.arange(len(ids)), held[ids]
        self.rank = held[term].astype(np.int32)
        n, mean, df = (self.n, lens.mean(), self.held) if corpus is None else (corpus.n, corpus.mean, corpus.df[ids])
        idf = np.log1p((n - df + 0.5) / (df + 0.5)).astype(np.float32)
        norm = (spec.k1 * (1 - spec.b + spec.b * lens / max(1.0, mean))).astype(np.float32)
        self.weight = idf[self.rank] * tf * np.float32(spec.k1 + 1) / (tf + norm[doc])
        self.start = np.append(np.flatnonzero(np.concatenate([[True], doc[1:] != doc[:-1]])), len(doc))
        # Of documents that may still be found: the postings of rarer terms, term by term (where each term's begin, documents,
        # weights), and a row of weights for each term that a share of 1 / DENSE of the documents holds.
        often = np.flatnonzero(self.held * DENSE >= self.n)
        self.row = np.full(len(ids), -1, np.int32)
        self.row[often] = np.arange(len(often))
        row = self.row[self.rank]
        rows = np.zeros((len(often), self.n))
        rows[row[row >= 0], doc[row >= 0]] = self.weight[row >= 0]
        rare = np.flatnonzero(row < 0)
        by_term = rare[np.argsort(self.rank[rare].astype(np.uint16) if len(ids) <= 1 << 16 else self.rank[rare], kind="stable")]
        begin = np.append(0, np.cumsum(np.where(self.row < 0, self.held, 0)))
        self.live = begin, doc[by_term].astype(np.int64), self.weight[by_term].astype(np.float64), rows, np.arange(self.n)
        self.left = self.n

    def query(self, seed: int) -> np.ndarray:
        """A document's terms that another document of the shard has too; with spec.terms the weightiest of them."""
        own = slice(self.start[seed], self.start[seed + 1])
        rank, weight = self.rank[own], self.weight[own]
        shared = self.held[rank] > 1
        rank, weight = rank[shared], weight[shared]
        return rank if self.terms is None else rank[np.lexsort((rank, -weight))[: self.terms]]

    def neighbours(self, seed: int, unused: np.ndarray) -> np.ndarray:
        """Unused documents that share a query term, best first; ties by place. What is used once stays so."""
        return np.fromiter(best_first(self.scores(seed, unused)), np.int64)

    def scores(self, seed: int, unused: np.ndarray) -> np.ndarray:
        """The score of each document, 0 for those used and those that share no query term."""
        left = np.count_nonzero(unused)
        begin, doc, weight, rows, alive = self.live
        if 8 * left < 7 * self.left:
            kept, stay = unused[doc], unused[alive]
            begin, doc, weight = np.append(0, np.cumsum(kept))[begin], doc[kept], weight[kept]
            self.live, self.left = (begin, doc, weight, rows.compress(stay, 1), alive[stay]), left
            rows, alive = self.live[3:]
        query = self.query(seed)
        row = self.row[query]
        rare, near, score = query[row < 0], np.zeros(len(alive)), np.zeros(self.n)
        spans = [slice(a, b) for a, b in zip(begin[rare].tolist(), begin[rare + 1].tolist())]
        if spans:
            score += np.bincount(np.concatenate([doc[x] for x in spans]), np.concatenate([weight[x] for x in spans]), self.n)
        for k in row[row >= 0].tolist():
            near += rows[k]
        score[alive] += near
        score[~unused] = 0
        return score


def best_first(score: np.ndarray) -> Iterator[int]:
    """Documents with a score, best first, ties by place; the FEW best are put in order without the rest."""
    found = np.flatnonzero(score)
    own = score[found]
    least = np.partition(own, -FEW)[-FEW] if len(own) > FEW else 0
    for part in (own >= least, own < least):
        yield from found[part][np.argsort(-own[part], kind="stable")].tolist()


def fill_windows(tokens: list[np.ndarray], spec: PackSpec, corpus: Corpus | None = None) -> Iterator[tuple[int, int, int, int, int]]:
    """(sequence, offset, document, start, length) of each piece. All windows but the last are full.

    A window starts with what the last one has cut off, or with the first unused document as its seed; the seed's
    unused neighbours follow, best first, then unused documents in order. What doesn't fit is cut and goes on in the
    next window as its seed.
    """
    n, index = len(tokens), Index(tokens, spec, corpus)
    unused, ahead = np.ones(n, bool), 0
    sequence = offset = 0
    doc, at, queue = -1, 0, iter(())
    while True:
        if doc < 0:
            doc = next((d for d in queue if unused[d]), -1)
            if doc < 0:
                while ahead < n and not unused[ahead]:
                    ahead += 1
                if ahead == n:
                    return
                doc = ahead
            unused[doc], at = False, 0
        if offset == 0:
            queue = best_first(index.scores(doc, unused)) if len(tokens[doc]) - at < spec.window else iter(())
        take = min(spec.window - offset, len(tokens[doc]) - at)
        yield sequence, offset, doc, at, take
        at, offset = at + take, offset + take
        if at == len(tokens[doc]):
            doc = -1
        if offset == spec.window:
            sequence, offset, queue = sequence + 1, 0, iter(())


def parts(batch: pa.RecordBatch, wide: int, data: int) -> Iterator[tuple[int, list[np.ndarray]]]:
    """(first row, token ids of each row) of runs of rows with about RUN_IDS ids, or one longer row."""
    flags, column = batch.column(wide).to_pylist(), batch.column(data)
    held, first, size = [], 0, 0
    for k in range(batch.num_rows):
        held.append(ids_of(column[k].as_py(), flags[k]))
        size += len(held[-1])
        if size >= RUN_IDS or k + 1 == batch.num_rows:
            yield first, held
            held, first, size = [], k + 1, 0


def corpus_of(coded: DataFrame) -> Corpus:
    """The statistics over all rows; the driver gets a row for each token id in use."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        df = np.zeros(1 << 16, np.int64)
        for batch in batches:
            for _, tokens in parts(batch, 0, 1):
                own = np.bincount(counted(tokens)[1])
                if len(own) > len(df):
                    df = np.append(df, np.zeros(len(own) - len(df), np.int64))
                df[: len(own)] += own
        held = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(held, pa.int64()), pa.array(df[held], pa.int64())], ["term", "df"])

    size = coded.agg(F.count("*").alias("n"), F.sum("n").alias("tokens")).first()
    found = coded.select("wide", "data").mapInArrow(tidied(run), "term long, df long").groupBy("term").agg(F.sum("df").alias("df")).collect()
    df = np.zeros(1 + max((r["term"] for r in found), default=0), np.int64)
    for r in found:
        df[r["term"]] = r["df"]
    return Corpus(size["n"], (size["tokens"] or 0) / max(1, size["n"]), df)


def places(names: Sequence[int | None], tokens: Sequence[np.ndarray], corpus: Corpus) -> np.ndarray:
    """Where documents stand among all: by the two weightiest terms (count times idf) that others have too, then by a hash."""
    doc, term, count = counted(tokens)
    df = corpus.df[term]
    weight = np.where(df > 1, np.log1p((corpus.n - df + 0.5) / (df + 0.5)) * count, 0)
    start = np.flatnonzero(np.concatenate([[True], doc[1:] != doc[:-1]]))
    tops = []
    for _ in range(2):
        best = np.flatnonzero(weight == np.maximum.reduceat(weight, start)[doc])
        best = best[np.concatenate([[True], doc[best][1:] != doc[best][:-1]])]
        tops.append(term[best].astype(np.int64) & 0xFFFFF)
        weight[best] = -1
    tail = [zlib.crc32(t.tobytes(), zlib.crc32(str(i).encode())) & 0x7FFFFF for i, t in zip(names, tokens)]
    return tops[0] << 43 | tops[1] << 23 | np.array(tail, np.int64)


def shard_cuts(placed: DataFrame, shards: int) -> np.ndarray:
    """Places at which a new shard begins, so that shards have about equal numbers of tokens; a few scalars for each shard reach the driver."""
    fine = np.array(range_bounds(placed, "place", 4 * shards), np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros(len(fine) + 1, np.int64)
        for batch in batches:
            np.add.at(sums, np.searchsorted(fine, batch.column(0).to_numpy()), batch.column(1).to_numpy())
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(sums)), pa.int64()), pa.array(sums, pa.int64())], ["k", "n"])

    sums = np.zeros(len(fine) + 1, np.int64)
    for r in placed.select("place", "n").mapInArrow(run, "k long, n long").groupBy("k").agg(F.sum("n").alias("n")).collect():
        sums[r["k"]] = r["n"]
    shard = np.minimum(shards - 1, (np.cumsum(sums) - sums) * shards // max(1, int(sums.sum())))
    return fine[shard[1:] > shard[:-1]]


def pack(docs: DataFrame, vocabulary: str, kind: str = "word_level", spec: PackSpec = PackSpec(), id_col: str = "doc_id", text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """(id, start, length, ids_crc32, doc_tokens, sequence_id, offset[, ids]), a row for each piece of a document.

    ids holds the piece's token ids as little-endian unsigned 32-bit integers.

    All documents are tokenised once and stored; BM25's statistics are those of all of them. Ordered by their weightiest
    terms, they are cut into shards of about spec.shard_bytes of text, whose number grows with the corpus; a task works
    off a run of shards, has one at a time in memory, and a shard holds no fewer than one whole document. Neighbours are looked for within the
    shard. Each shard's windows are full but for its last. sequence_id is shard * 2^32 + window.

    Null texts count as empty: the end id alone. Rows that repeat an id are packed each. Equal rows come in any order,
    which shows in no column. An empty table gives an empty result.
    """
    ship(docs.sparkSession)
    total = docs.agg(F.sum(F.octet_length(F.coalesce(F.col(text_col), F.lit(""))) + 1)).first()[0] or 0
    shards = max(1, -(-int(total) // spec.shard_bytes))
    coded = stored(tokenised(docs, vocabulary, kind, spec.end_id, id_col, text_col, spec.cache_pieces), "tokens")
    corpus = corpus_of(coded)

    def placed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        for batch in batches:
            names = batch.column(0).to_pylist()
            for first, tokens in parts(batch, 2, 3):
                found = places(names[first : first + len(tokens)], tokens, corpus)
                yield pa.RecordBatch.from_arrays([pa.array(found), batch.column(1).slice(first, len(tokens))], ["place", "n"])

    cuts = shard_cuts(stored(coded.mapInArrow(tidied(placed), "place long, n long"), "places"), shards) if shards > 1 else np.zeros(0, np.int64)
    shards = len(cuts) + 1

    def sharded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        for batch in batches:
            names = batch.column(0).to_pylist()
            for first, tokens in parts(batch, 2, 3):
                n = len(tokens)
                own = np.searchsorted(cuts, places(names[first : first + n], tokens, corpus)) if shards > 1 else np.zeros(n, np.int64)
                yield pa.RecordBatch.from_arrays([*[batch.column(k).slice(first, n) for k in (0, 2, 3)], pa.array(own.astype(np.int32))], ["id", "wide", "data", "shard"])

    rows = coded.mapInArrow(tidied(sharded), "id long, wide boolean, data binary, shard int")
    width = min(shards, max(shuffle_width(docs.sparkSession), -(-int(total) // TASK_BYTES)))
    task = (F.col("shard").cast("long") * width / shards).cast("int")
    dealt = rows.repartitionById(width, task).sortWithinPartitions("shard", F.col("id").asc_nulls_first(), "data")
    columns = ("id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset") + (("ids",) if with_ids else ())

    def packed(number: int, ids: list, tokens: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        out: list[list] = [[] for _ in columns]
        kinds = [*[pa.int64()] * 7, pa.binary()]
        for sequence, offset, d, start, length in fill_windows(tokens, spec, corpus):
            piece = tokens[d][start : start + length].astype("<u4").tobytes()
            row = [ids[d], start, length, zlib.crc32(piece), len(tokens[d]), (number << 32) + sequence, offset]
            for column, x in zip(out, [*row, piece] if with_ids else row):
                column.append(x)
            if len(out[0]) == PIECES:
                yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(out, kinds)], list(columns))
                out = [[] for _ in columns]
        yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(out, kinds)], list(columns))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()
        own, ids, tokens = None, [], []
        for batch in batches:
            for name, wide, data, number in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), batch.column(3).to_pylist()):
                if number != own:
                    if ids:
                        yield from packed(own, ids, tokens)
                    own, ids, tokens = number, [], []
                ids.append(name)
                tokens.append(ids_of(data.as_py(), wide))
        if ids:
            yield from packed(own, ids, tokens)

    schema = "id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + (", ids binary" if with_ids else "")
    return dealt.mapInArrow(tidied(run), schema)
