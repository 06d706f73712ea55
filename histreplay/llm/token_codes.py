"""Token files of directly addressable codes: ids in chunk levels, continuation bitmaps with rank directories.

Level 0 holds the low 8 bits of every id in order. A bitmap says for each entry whether the id goes on in the next
level, where it is found at the number of ones before it; a directory with the ones before each block of 512 entries
makes that a few operations. So any token of a segment is read without decoding others.

A segment is a row of a Parquet file with its first and last place among its columns, and pages hold few rows: a reader
that asks for a place opens one part, and of that the pages which the file's own index names.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from histreplay.llm.common import bucket_of, range_bounds, scratch, ship, shuffle_width, tidied
from histreplay.llm.tokenise import ids_of, tokenised

#: Fixed values of the format: magic, bits of a chunk, entries of a directory block.
MAGIC, CHUNK_BITS, BLOCK = b"DAC1", 8, 512
#: A segment is closed when it has this many ids.
SEGMENT_IDS = 1 << 14
#: Rows of a page of the files, and bytes of a part's source files, about.
PAGE_ROWS, PART_BYTES = 4, 256 << 20


def encode_codes(ids: np.ndarray) -> bytes:
    """Unsigned 32-bit ids as a sequence of levels: count, then for each level its chunks, bitmap and directory."""
    rest, out = ids.astype(np.uint32), [MAGIC, struct.pack("<Q", len(ids))]
    levels: list[bytes] = []
    while len(rest):
        more = rest >> CHUNK_BITS
        flags = more > 0
        bitmap = np.packbits(flags, bitorder="little")
        ones = np.add.reduceat(flags, np.arange(0, len(flags), BLOCK), dtype=np.int64)
        directory = (np.cumsum(ones) - ones).astype("<u4")
        levels.append(struct.pack("<Q", len(rest)) + (rest & 0xFF).astype(np.uint8).tobytes() + bitmap.tobytes() + directory.tobytes())
        rest = more[flags]
    return b"".join([*out, struct.pack("<B", len(levels)), *levels])


class Codes:
    """Reads encode_codes' bytes: the whole, or single ids by rank."""

    def __init__(self, data: bytes) -> None:
        if data[:4] != MAGIC:
            raise ValueError("not a code sequence")
        (self.n,), at = struct.unpack_from("<Q", data, 4), 12
        self.levels = []
        (depth,) = struct.unpack_from("<B", data, at)
        at += 1
        for _ in range(depth):
            (n,) = struct.unpack_from("<Q", data, at)
            at += 8
            parts = []
            for kind, size in ((np.uint8, n), (np.uint8, -(-n // 8)), (np.dtype("<u4"), -(-n // BLOCK))):
                parts.append(np.frombuffer(data, kind, size, at))
                at += parts[-1].nbytes
            self.levels.append(tuple(parts))

    def __len__(self) -> int:
        return self.n

    def __getitem__(self, k: int) -> int:
        if not 0 <= k < self.n:
            raise IndexError(k)
        value, shift = 0, 0
        for chunks, bitmap, directory in self.levels:
            value |= int(chunks[k]) << shift
            if not bitmap[k >> 3] >> (k & 7) & 1:
                break
            block = k - k % BLOCK
            k = int(directory[k // BLOCK]) + int(np.unpackbits(bitmap[block >> 3 : (k >> 3) + 1], bitorder="little")[: k - block].sum())
            shift += CHUNK_BITS
        return value

    def decode(self) -> np.ndarray:
        value = np.zeros(0, np.uint32)
        for chunks, bitmap, _ in reversed(self.levels):
            flags = np.unpackbits(bitmap, count=len(chunks), bitorder="little").astype(bool)
            own = chunks.astype(np.uint32)
            own[flags] |= value << CHUNK_BITS
            value = own
        return value


def _parts(docs: DataFrame) -> int:
    """As many as the session's shuffle partitions, or more where the plan's own estimate of its source is larger."""
    size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return max(shuffle_width(docs.sparkSession), size // PART_BYTES if size < 1 << 60 else 0)


def write_tokens(docs: DataFrame, path: str, vocabulary: str, kind: str = "byte_level", end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Encodes whole texts, adds end_id to each, and writes segments of codes in ascending id order to path.

    Texts are encoded where they are read; their ids are dealt by ranges of the document's id and sorted within, so
    that part and place give the order; documents of one id go by their token ids. Each row is one segment of whole
    documents: its first place and the place after its last (within its part), the documents' ids and token counts, and
    the codes. Spark's committer writes the files, so a lost executor's part is written again. A small table beside
    them, _parts, has each part's first place among all. Null texts count as empty and null ids come first. An empty
    table writes no segment.
    """
    rows = tokenised(docs, vocabulary, kind, end_id, id_col, text_col)
    bounds = range_bounds(docs.select(F.col(id_col).cast("long").alias("id")), "id", _parts(docs))
    part = bucket_of(F.col("id"), bounds)
    ordered = rows.withColumn("part", part).repartitionById(len(bounds) + 1, "part").sortWithinPartitions(F.col("part"), F.col("id").asc_nulls_first(), "data")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: int | None = None
        first = size = 0
        held: list[tuple[int | None, np.ndarray]] = []

        def close() -> pa.RecordBatch:
            nonlocal first, size, held
            codes = encode_codes(np.concatenate([x[1] for x in held]))
            columns = [[own], [first], [first + size], [[x[0] for x in held]], [[len(x[1]) for x in held]], [codes]]
            kinds = (pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary())
            first, size, held = first + size, 0, []
            return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(columns, kinds)], ["part", "first", "after", "ids", "n_tokens", "codes"])

        for batch in batches:
            ids, wide, numbers = (batch.column(k).to_pylist() for k in (0, 1, 3))
            for name, flag, number, data in zip(ids, wide, numbers, batch.column(2)):
                if number != own:
                    if held:
                        yield close()
                    own, first = number, 0
                held.append((name, ids_of(data.as_py(), flag)))
                size += len(held[-1][1])
                if size >= SEGMENT_IDS:
                    yield close()
        if held:
            yield close()

    coded = ordered.select("id", "wide", "data", "part").mapInArrow(tidied(run), "part int, first long, after long, ids array<long>, n_tokens array<long>, codes binary")
    pages = {"parquet.page.row.count.limit": PAGE_ROWS, "parquet.page.size.row.check.min": PAGE_ROWS, "parquet.page.size.row.check.max": PAGE_ROWS}
    coded.write.options(**pages).partitionBy("part").parquet(path)
    table = _segments(docs.sparkSession, path)
    totals = sorted((r["part"], r["n"]) for r in table.groupBy("part").agg(F.max("after").alias("n")).collect())
    starts = np.cumsum([0, *[n for _, n in totals]]).tolist()
    docs.sparkSession.createDataFrame([(p, s, n) for (p, n), s in zip(totals, starts)], "part int, start long, n long").coalesce(1).write.parquet(f"{path}/_parts")


def _segments(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("first long, after long, ids array<long>, n_tokens array<long>, codes binary, part int").parquet(path)


def _starts(spark: SparkSession, path: str) -> list:
    """(part, start, n) of each part in order; some tens of thousands of rows at most."""
    return spark.read.schema("part int, start long, n long").parquet(f"{path}/_parts").orderBy("part").collect()


def read_documents(spark: SparkSession, path: str) -> DataFrame:
    """(id, start, n_tokens, ids_crc32) of each document, from the files alone. start counts the ids of all before it."""
    ship(spark)
    before = {r["part"]: r["start"] for r in _starts(spark, path)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, first, ids, counts, codes in zip(*(batch.column(k) for k in range(5))):
                tokens, start = Codes(codes.as_py()).decode().astype("<u4"), before[part.as_py()] + first.as_py()
                counts = np.array(counts.as_py(), np.int64)
                ends = np.cumsum(counts)
                crcs = [zlib.crc32(tokens[e - n : e].tobytes()) for e, n in zip(ends, counts)]
                columns = [ids.values, pa.array(start + ends - counts), pa.array(counts), pa.array(crcs, pa.int64())]
                yield pa.RecordBatch.from_arrays(columns, ["id", "start", "n_tokens", "ids_crc32"])

    table = _segments(spark, path).select("part", "first", "ids", "n_tokens", "codes")
    return table.mapInArrow(tidied(run), "id long, start long, n_tokens long, ids_crc32 long")


def read_tokens(spark: SparkSession, path: str, place: int, count: int) -> DataFrame:
    """(place, token) of up to `count` ids from a place among all of the corpus, by direct access into their segments.

    Only the parts that hold the places are opened, and of those the pages whose segments do. Places beyond the end
    give no row.
    """
    ship(spark)
    end = place + count
    held = [r for r in _starts(spark, path) if r["start"] < end and r["start"] + r["n"] > place]
    before = {r["part"]: r["start"] for r in held}
    wanted = F.lit(False)
    for part, start in before.items():
        wanted = wanted | ((F.col("part") == part) & (F.col("first") < end - start) & (F.col("after") > place - start))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, first, codes in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                own, at = Codes(codes.as_py()), before[part] + first
                found = range(max(place, at), min(end, at + len(own)))
                yield pa.RecordBatch.from_arrays([pa.array(found, pa.int64()), pa.array([own[k - at] for k in found], pa.int64())], ["place", "token"])

    return _segments(spark, path).filter(wanted).select("part", "first", "codes").mapInArrow(run, "place long, token long")


def token_files(docs: DataFrame, vocabulary: str, **how) -> str:
    """Writes the files to a new folder of the shared one and returns its path."""
    import uuid

    path = f"{scratch(docs.sparkSession)}/tokens-{uuid.uuid4().hex}"
    write_tokens(docs, path, vocabulary, **how)
    return path
