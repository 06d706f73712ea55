"""Quality rules whose cutoffs come with an exact bound on how many good documents they reject."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from histreplay.llm.common import ship, stored, tidied
from histreplay.llm.textbytes import _SPACE, slices, windows, word_hashes, word_spans

#: The base rules' symbols.
SYMBOLS = b"#*$%&|<>"
#: Rules: name, measure in SQL over the columns of measures(); a document is rejected from the cutoff on, never at 0.
RULES = (
    ("symbols", "n_symbols / greatest(n_words, 1)"),
    ("punctuation", "n_punctuation / greatest(n_words, 1)"),
    ("capitals", "n_capitals / greatest(word_chars, 1)"),
    ("word_length", "word_chars / greatest(n_words, 1) / 40"),
    ("repeated_lines", "n_dup_lines / greatest(n_lines, 1)"),
    ("repeated_words", "n_repeat_words / greatest(n_words, 1)"),
)
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_punctuation", "n_capitals")


@dataclass(frozen=True)
class RiskSpec:
    """risk: the share of a stratum's good documents that all rules together may reject, of those that pass the base test;

    miss: the chance that the guarantee fails in any stratum; a rule's cutoffs are `steps` levels, each of which reaches
    another `tail` of the documents not labelled good; lift: how many times that share a level must reach of those
    labelled bad. strata: the most that may occur.
    """

    risk: float = 0.05
    miss: float = 0.1
    steps: int = 60
    tail: float = 0.005
    lift: float = 4.0
    strata: int = 1000
    good: int = 1


def _flags(values: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(values)] = True
    return out


_SYMBOL = _flags(SYMBOLS)
_PUNCT = _flags(bytes(c for c in range(33, 127) if not chr(c).isalnum()))
_CAPITAL = _flags(bytes(range(65, 91)))


def _per_document(flag: np.ndarray, off: np.ndarray) -> np.ndarray:
    sums = np.zeros(len(flag) + 1, np.int64)
    np.cumsum(flag, out=sums[1:])
    return sums[off[1:]] - sums[off[:-1]]


def _lines(data: np.ndarray, off: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each document, lines with a word, and those of them that equal an earlier line."""
    n = len(off) - 1
    if not len(data):
        return np.zeros(n, np.int64), np.zeros(n, np.int64)
    breaks = np.flatnonzero(data == 10)
    heads = np.unique(np.concatenate([off[:-1], breaks + 1, off[1:]]))
    heads = heads[heads < len(data)]
    tails = np.append(heads[1:], len(data))
    tails = tails - (data[tails - 1] == 10)
    words = np.searchsorted(start, tails) - np.searchsorted(start, heads)
    heads, tails = heads[words > 0], tails[words > 0]
    h = word_hashes(data, heads, tails, False)
    doc = np.searchsorted(off, heads, "right") - 1
    total = np.bincount(doc, minlength=n)
    order = np.lexsort((h, doc))
    same = np.zeros(len(h), bool)
    same[1:] = (h[order][1:] == h[order][:-1]) & (doc[order][1:] == doc[order][:-1])
    return total, np.bincount(doc[order][same], minlength=n)


def measure_slice(data: np.ndarray, off: np.ndarray) -> list[np.ndarray]:
    """COUNTS for each document of a slice."""
    n = len(off) - 1
    start, end, at = word_spans(data, off)
    n_words = np.diff(at)
    inside = ~_SPACE[data]
    chars = _per_document(inside & ((data & 0xC0) != 0x80), off)
    n_lines, n_dup = _lines(data, off, start)
    every = windows(word_hashes(data, start, end, False), 3)
    repeated = np.zeros(n, np.int64)
    for d in np.flatnonzero(n_words >= 4):
        own = every[at[d] : at[d + 1] - 2]
        order = np.argsort(own, kind="stable")
        equal = own[order][1:] == own[order][:-1]
        if equal.any():
            found = np.zeros(len(own), bool)
            found[order[1:][equal]] = True
            found[order[:-1][equal]] = True
            covered = np.zeros(len(own) + 2, bool)
            for k in range(3):
                covered[k : k + len(own)] |= found
            repeated[d] = covered.sum()
    return [n_words, chars, _per_document(_SYMBOL[data], off), n_dup, repeated, n_lines, _per_document(_PUNCT[data], off), _per_document(_CAPITAL[data], off)]


def measures(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum_col: str = "lang") -> DataFrame:
    """(id, stratum, *COUNTS) of whole texts; null texts have no words, a null stratum is `none`."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, data, off in slices(batch.column(2)):
                n = len(off) - 1
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, n), batch.column(1).slice(first, n), *[pa.array(x, pa.int64()) for x in measure_slice(data, off)]], ["id", "stratum", *COUNTS])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(stratum_col).cast("string"), F.lit("none")).alias("stratum"), F.col(text_col).alias("text"))
    return rows.mapInArrow(tidied(run), "id long, stratum string, " + ", ".join(f"{c} long" for c in COUNTS))


def binomial_tail(k: int, n: int, p: float) -> float:
    """P(X <= k) for X binomial with n trials of chance p."""
    if k >= n:
        return 1.0
    logs = [math.lgamma(n + 1) - math.lgamma(j + 1) - math.lgamma(n - j + 1) + j * math.log(p) + (n - j) * math.log1p(-p) for j in range(k + 1)]
    top = max(logs)
    return min(1.0, math.exp(top) * sum(math.exp(x - top) for x in logs))


def upper_bound(k: int, n: int, miss: float) -> float:
    """The exact (Clopper-Pearson) upper bound on a chance of which k of n trials were seen: wrong with a chance of miss."""
    if k >= n:
        return 1.0
    low, high = k / n, 1.0
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if mid > 0 and binomial_tail(k, n, mid) > miss else (low, mid)
        if mid == 0:
            low = 1e-12
    return high


def joint_path(bad: dict[str, list[int]], spec: RiskSpec) -> list[tuple[int, ...]]:
    """Levels of all rules at each step of a stratum's path, from bad[rule][k]: documents labelled bad that level k + 1 reaches first.

    Each step moves the rule on whose next levels reach the most bad documents a level, until spec.lift is missed. If
    none is labelled bad, all rules go on together.
    """
    total = max((sum(own) for own in bad.values()), default=0)
    if not total:
        return [(k + 1,) * len(RULES) for k in range(spec.steps)]
    levels, path = [0] * len(RULES), []
    while True:
        best = (spec.lift, 0, 0)
        for r, (name, _) in enumerate(RULES):
            reached = 0
            for k in range(levels[r], spec.steps):
                reached += bad[name][k]
                best = max(best, (reached / total / (spec.tail * (k + 1 - levels[r])), -r, levels[r] - k - 1))
        if not best[2]:
            return path
        levels[-best[1]] -= best[2]
        path.append(tuple(levels))


def certify(rejected: dict[str, list[int]], good: dict[str, int], spec: RiskSpec) -> dict[str, tuple[int, float]]:
    """(step, bound) by stratum: the last step of the path up to which every step's rejections are proven rare enough.

    rejected[s][t] counts the good documents of a stratum that step t + 1 rejects. The steps of a stratum are tested in
    order up to the first failure, which needs no correction. Strata with enough good documents to prove anything share
    the chance of a miss evenly, and one that passes its whole path leaves its share to the others.
    """
    able = sorted(s for s, n in good.items() if n and (1 - spec.risk) ** n <= spec.miss)
    share, at, open_ = {s: spec.miss / len(able) for s in able}, dict.fromkeys(able, 0), set(able)
    while True:
        done = set()
        for s in sorted(open_):
            while at[s] < len(rejected[s]) and binomial_tail(rejected[s][at[s]], good[s], spec.risk) <= share[s]:
                at[s] += 1
            if at[s] == len(rejected[s]):
                done.add(s)
        open_ -= done
        if not done or not open_:
            break
        for s in open_:
            share[s] += sum(share[d] for d in done) / len(open_)
    return {s: (k, upper_bound(rejected[s][k - 1], good[s], share[s])) for s, k in at.items() if k}


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def _value(sql: str) -> Column:
    return F.expr(f"cast({sql} as double)")


def _levels(measured: DataFrame, cuts: DataFrame, steps: int) -> DataFrame:
    """Adds for each rule the first level whose cutoff a document's measure reaches; steps + 1 if none does."""
    level = lambda own, value: F.when(value > 0, F.size(F.filter(own, lambda cut: cut > value)) + 1).otherwise(steps + 1)
    rows = measured.join(F.broadcast(cuts), "stratum")
    return rows.select("id", "stratum", *[level(F.col(f"cuts_{n}"), _value(m)).alias(n) for n, m in RULES])


def calibrate(measured: DataFrame, labels: DataFrame, spec: RiskSpec = RiskSpec(), id_col: str = "doc_id", label_col: str = "quality") -> dict[str, tuple[list[float], float, int]]:
    """Stratum to (cutoff of each rule, bound, good documents seen), over documents that pass the base test.

    The levels of a rule are upper quantiles of its measure over all documents of the stratum that are not labelled
    good, and the path through the rules' levels follows the documents labelled bad; so those labelled good, all of
    them, are a holdout for it. A document counts as good if all of its labels are, as bad if it has other labels. What
    reaches the driver are spec.steps numbers for each stratum and rule; a stratum without enough good documents to
    prove the bound gets no cutoffs. A rule that the path has not moved has an infinite cutoff.
    """
    marks = labels.groupBy(F.col(id_col).alias("id")).agg(F.min(label_col).alias("low"), F.max(label_col).alias("high")).filter("low is not null")
    marks = marks.select("id", ((F.col("low") == spec.good) & (F.col("high") == spec.good)).alias("good"))
    passed = measured.filter(~base_failed())
    shares = F.array(*[F.lit(1 - spec.tail * t) for t in range(1, spec.steps + 1)])
    cuts = passed.join(marks.filter("good"), "id", "left_anti").groupBy("stratum").agg(*[F.percentile_approx(_value(m), shares, 10_000).alias(f"cuts_{n}") for n, m in RULES])
    cuts = stored(cuts.limit(spec.strata + 1), "cuts")
    if cuts.count() > spec.strata:
        raise ValueError(f"more than {spec.strata} strata")
    rows = stored(_levels(passed.join(marks, "id"), cuts, spec.steps).join(marks, "id"), "levels")
    bad: dict[str, dict[str, list[int]]] = {}
    each = F.explode(F.array(*[F.struct(F.lit(n).alias("rule"), F.col(n).alias("level")) for n, _ in RULES])).alias("x")
    for r in rows.filter("not good").select("stratum", each).groupBy("stratum", "x.rule", "x.level").agg(F.count("*").alias("n")).collect():
        bad.setdefault(r["stratum"], {n: [0] * (spec.steps + 1) for n, _ in RULES})[r["rule"]][r["level"] - 1] += r["n"]
    paths = {r["stratum"]: joint_path(bad.get(r["stratum"], {}), spec) for r in cuts.select("stratum").collect()}
    first = []
    for s, path in paths.items():
        own = [[next((p for p, levels in enumerate(path) if levels[r] >= k), len(path)) for k in range(1, spec.steps + 1)] + [len(path)] for r in range(len(RULES))]
        first.append((s, *own))
    table = rows.sparkSession.createDataFrame(first, "stratum string, " + ", ".join(f"first_{n} array<int>" for n, _ in RULES))
    steps = F.least(*[F.get(F.col(f"first_{n}"), F.col(n) - 1) for n, _ in RULES])
    counts = {s: [0] * (len(path) + 1) for s, path in paths.items()}
    for r in rows.filter("good").join(F.broadcast(table), "stratum").groupBy("stratum", steps.alias("step")).agg(F.count("*").alias("n")).collect():
        counts[r["stratum"]][r["step"]] += r["n"]
    seen = {s: sum(own) for s, own in counts.items()}
    proven = certify({s: np.cumsum(own[:-1]).tolist() for s, own in counts.items()}, seen, spec)
    at = {r["stratum"]: r for r in cuts.filter(F.col("stratum").isin(*proven)).collect()} if proven else {}
    cutoff = lambda s, n, level: at[s][f"cuts_{n}"][level - 1] if level else math.inf
    return {s: ([cutoff(s, n, paths[s][step - 1][r]) for r, (n, _) in enumerate(RULES)], bound, seen[s]) for s, (step, bound) in proven.items()}


def judge(docs: DataFrame, labels: DataFrame, spec: RiskSpec = RiskSpec(), id_col: str = "doc_id", text_col: str = "text", stratum_col: str = "lang") -> DataFrame:
    """(id, stratum, *COUNTS, base_failed, rejected_by, kept), a row for each document.

    base_failed: under 50 words, or more than half of the words in repeated 3-word windows. rejected_by names the rules
    whose measure reaches the cutoff of the document's stratum, comma-joined; kept is neither. Strata without cutoffs
    reject nothing more. Null and empty texts fail the base. Repeated rows are judged each; an empty table or no labels
    give no cutoffs.
    """
    measured = stored(measures(docs, id_col, text_col, stratum_col), "measures")
    cutoffs = calibrate(measured, labels, spec, id_col)
    kind = "cut_of string, " + ", ".join(f"cut_{n} double" for n, _ in RULES)
    table = docs.sparkSession.createDataFrame([(s, *cuts) for s, (cuts, _, _) in cutoffs.items()], kind)
    fails = [F.when((_value(m) > 0) & (_value(m) >= F.col(f"cut_{n}")), F.lit(n)) for n, m in RULES]
    judged = measured.join(F.broadcast(table), F.col("stratum") == F.col("cut_of"), "left")
    judged = judged.withColumns({"base_failed": base_failed(), "rejected_by": F.array_join(F.array_compact(F.array(*fails)), ",")})
    return judged.select(*measured.columns, "base_failed", "rejected_by", (~F.col("base_failed") & (F.col("rejected_by") == "")).alias("kept"))
