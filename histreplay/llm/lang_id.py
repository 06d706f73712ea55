"""Language identification by hyperdimensional letter n-gram profiles.

Every letter has a fixed random vector of +1 and -1; a trigram's is the product of its letters' vectors, rotated by
their places; a text's is the sum over its trigrams; a language's prototype is the sum over its texts. A text gets the
language of the nearest prototype by cosine.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from histreplay.llm.common import by_ids, release, ship, small_batches, stored, tidied, unused, written
from histreplay.llm.textbytes import mix

#: Latin letters up to U+024F and the space have places in a table; any other letter is folded into the places after.
_TABLE = 0x250
_PLACES = 128
UNKNOWN = "und"
#: Trigram vectors that a task keeps, a byte a dimension.
VECTORS = 20_000


@dataclass(frozen=True)
class LangSpec:
    """dims: length of the vectors; languages: the most that may be learned, which bounds what the driver gathers."""

    dims: int = 1024
    seed: int = 5
    languages: int = 1000


def _letter_places() -> np.ndarray:
    """Code point to letter place: 0 for what is no letter, lower case for letters in the table."""
    out = np.zeros(_TABLE, np.int64)
    seen: dict[str, int] = {}
    for c in range(_TABLE):
        if chr(c).isalpha():
            low = chr(c).lower()[:1]
            out[c] = 1 + seen.setdefault(low, len(seen) % (_PLACES - 1))
    return out


_TO_PLACE = _letter_places()


def letters(text: str) -> np.ndarray:
    """Letter places of a text, each run of anything else as one 0, one 0 at each end."""
    code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    place = _TO_PLACE[np.minimum(code, _TABLE - 1)]
    far = np.flatnonzero(code >= _TABLE)
    if len(far):
        kinds, back = np.unique(code[far], return_inverse=True)
        own = [1 + int(mix(np.array([ord(chr(c).lower()[:1])], np.uint64))[0] % np.uint64(_PLACES - 1)) if chr(c).isalpha() else 0 for c in kinds]
        place[far] = np.array(own, np.int64)[back]
    place = np.concatenate([[0], place, [0]])
    keep = np.ones(len(place), bool)
    keep[1:] = (place[1:] > 0) | (place[:-1] > 0)
    return place[keep]


def trigrams(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Codes and counts of the trigrams of a text; none without a letter."""
    p = letters(text)
    if len(p) < 3:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.unique((p[:-2] * _PLACES + p[1:-1]) * _PLACES + p[2:], return_counts=True)


class Memory:
    """Trigram vectors by code, made when first needed; a task has one of its own, so its memory ends with the task."""

    def __init__(self, spec: LangSpec) -> None:
        bits = np.random.Generator(np.random.PCG64(spec.seed)).integers(0, 2, (_PLACES, spec.dims), np.int8)
        self.items = 2 * bits - 1
        self.place = np.full(_PLACES**3, -1, np.int32)
        self.rows = np.empty((VECTORS, spec.dims), np.int8)
        self.used = 0

    def of(self, codes: np.ndarray) -> np.ndarray:
        """Row numbers of the codes' vectors in rows. The table starts anew when they don't fit."""
        if len(codes) > VECTORS:
            raise ValueError("more trigrams at once than vectors are kept")
        new = codes[self.place[codes] < 0]
        if self.used + len(new) > VECTORS:
            self.place[:] = -1
            self.used, new = 0, codes
        if len(new):
            a, b, c = new // _PLACES**2, new // _PLACES % _PLACES, new % _PLACES
            self.rows[self.used : self.used + len(new)] = np.roll(self.items[a], 2, 1) * np.roll(self.items[b], 1, 1) * self.items[c]
            self.place[new] = np.arange(self.used, self.used + len(new))
            self.used += len(new)
        return self.place[codes]

    def bundle(self, codes: np.ndarray, counts: np.ndarray) -> np.ndarray:
        out = np.zeros(self.items.shape[1], np.float32)
        for k in range(0, len(codes), 2048):
            at = self.of(codes[k : k + 2048])
            out += counts[k : k + 2048].astype(np.float32) @ self.rows[at].astype(np.float32)
        return out


def learn(labelled: DataFrame, spec: LangSpec = LangSpec(), text_col: str = "text", lang_col: str = "lang") -> dict[str, np.ndarray]:
    """Prototypes by language. Each text counts the same, whatever its length; null texts and languages are left out.

    A task hands on one vector for each language it saw; these are summed by place and language on the executors, and
    spec.dims numbers for each language, at most spec.languages of them, reach the driver.
    """
    ship(labelled.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, sums = Memory(spec), {}
        for batch in batches:
            for lang, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                codes, counts = trigrams(text.as_py())
                if len(codes):
                    v = own.bundle(codes, counts)
                    sums[lang] = sums.get(lang, 0) + np.rint(v * (1e6 / max(1e-9, float(np.linalg.norm(v))))).astype(np.int64)
        names, values = list(sums), list(sums.values())
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(values, pa.list_(pa.int64()))], ["lang", "v"])

    rows = labelled.select(F.col(lang_col).alias("lang"), F.col(text_col).alias("text")).filter("lang is not null and text is not null")
    sums = rows.mapInArrow(tidied(run), "lang string, v array<long>").select("lang", F.posexplode("v").alias("k", "x"))
    table = sums.groupBy("lang", "k").agg(F.sum("x").alias("x")).groupBy("lang").agg(F.sort_array(F.collect_list(F.struct("k", "x"))).alias("v"))
    with small_batches(labelled.sparkSession):
        found = {r["lang"]: np.array([p["x"] for p in r["v"]], np.float64) for r in table.limit(spec.languages + 1).collect()}
    if len(found) > spec.languages:
        raise ValueError(f"more than {spec.languages} languages; raise LangSpec.languages if that is meant")
    return found


def predict(docs: DataFrame, prototypes: dict[str, np.ndarray], spec: LangSpec = LangSpec(), text_col: str = "text", names: tuple[str, ...] = ("lang_pred", "score")) -> DataFrame:
    """The columns of docs but the text, and the predicted language and its score under the two names.

    score is the cosine with the nearest prototype, 0 where it is negative; the smaller name wins a tie. Null texts,
    texts without a letter, and all texts if nothing was learned, get `und` and 0. Only the text decides. A third name
    adds the number of a text's trigrams.
    """
    ship(docs.sparkSession)
    langs = sorted(prototypes)
    units = np.array([prototypes[n] / max(1e-9, np.linalg.norm(prototypes[n])) for n in langs], np.float32)
    rest = [f for f in docs.schema.fields if f.name != text_col]
    columns = [*[f.name for f in rest], *names]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Memory(spec)
        for batch in batches:
            found, scores, sizes = [], [], []
            for text in batch.column(batch.num_columns - 1):
                codes, counts = trigrams(text.as_py() or "")
                sizes.append(int(counts.sum()))
                if not len(codes) or not langs:
                    found.append(UNKNOWN)
                    scores.append(0.0)
                    continue
                v = own.bundle(codes, counts)
                cosine = units @ (v / max(1e-9, float(np.linalg.norm(v))))
                k = int(cosine.argmax())
                found.append(langs[k])
                scores.append(min(1.0, max(0.0, float(cosine[k]))))
            own_columns = [pa.array(found, pa.string()), pa.array(scores, pa.float64()), pa.array(sizes, pa.int64())]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *own_columns[: len(names)]], columns)

    kinds = T.StructType([*rest, *[T.StructField(n, k) for n, k in zip(names, (T.StringType(), T.DoubleType(), T.LongType()))]])
    return docs.select(*[F.col(f.name) for f in rest], text_col).mapInArrow(tidied(run), kinds)


def held_out(id_col: str = "doc_id") -> Column:
    """A fixed quarter of the documents, by the checksum of the id; a null id is held out."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 == 2, F.lit(True))


def identify(docs: DataFrame, spec: LangSpec = LangSpec(), id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """(id, held_out, lang_pred, score) of each document, learned from the languages of those not held out."""
    prototypes = learn(docs.filter(~held_out(id_col)), spec, text_col, lang_col)
    rows = docs.select(F.col(id_col).alias("id"), held_out(id_col).alias("held_out"), F.col(text_col).alias("text"))
    return predict(rows, prototypes, spec).select("id", "held_out", "lang_pred", "score")


#: The share of the usual score of its language and size that a text must have, and how many texts tell what is usual.
USUAL_SHARE = 0.5
USUAL_TEXTS = 20


def keep_identified(docs: DataFrame, spec: LangSpec = LangSpec(), least: float = 0.0, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """The documents with an identified language and a score of `least` or more; all columns stay.

    A text must also reach USUAL_SHARE of the median score that the labelled texts of its predicted language have, those
    with as many trigrams up to a power of two. Where USUAL_TEXTS of them are lacking, the next smaller size counts;
    without any, the text stays. If nothing was learned, all texts with a letter stay.

    Texts alone decide, so what is rejected is written as the texts' ids, sizes and hashes, and taken out by those. At
    most some tens of numbers for each language reach the driver.
    """
    since = written()
    prototypes = learn(docs.filter(~held_out(id_col)), spec, text_col, lang_col)
    text = F.coalesce(F.col(text_col), F.lit(""))
    keys = dict(zip(unused(docs.columns, "id_of", "bytes", "hash"), (F.col(id_col), F.octet_length(text), F.xxhash64(text))))
    own = ~held_out(id_col) & F.col(lang_col).isNotNull()
    rows = docs.select(*[c.alias(k) for k, c in keys.items()], own.alias("__own"), F.col(lang_col).alias("__lang"), F.col(text_col).alias("text"))
    found = stored(predict(rows, prototypes, spec, names=("lang_pred", "score", "grams")).withColumn("level", F.floor(F.log2(F.greatest("grams", F.lit(1)))).cast("int")), "languages")
    usual: dict[str, dict[int, float]] = {}
    labelled = found.filter((F.col("__own")) & (F.col("__lang") == F.col("lang_pred")))
    for r in labelled.groupBy("lang_pred", "level").agg(F.count("*").alias("n"), F.percentile_approx("score", 0.5).alias("mid")).collect():
        if r["n"] >= USUAL_TEXTS:
            usual.setdefault(r["lang_pred"], {})[r["level"]] = r["mid"]
    bounds = [(lang, level, max(least, USUAL_SHARE * mid[max(k for k in mid if k <= level)])) for lang, mid in usual.items() for level in range(min(mid), 64)]
    table = docs.sparkSession.createDataFrame(bounds, "lang_pred string, level int, bound double")
    judged = found.join(F.broadcast(table), ["lang_pred", "level"], "left")
    low = (F.col("lang_pred") != UNKNOWN) & (F.col("score") < F.coalesce("bound", F.lit(least)))
    gone = stored(judged.filter((F.col("grams") == 0) | low).select(*keys).distinct(), "unidentified")
    release(docs.sparkSession, since, keep=1)
    return by_ids(docs.withColumns(keys), gone, list(keys), "left_anti").select(*docs.columns)
