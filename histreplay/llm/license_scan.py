"""Licence detection by ordered signature rules, in SQL expressions alone."""

from __future__ import annotations

import json
import re
from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from histreplay.llm.license_texts import SENTENCES

#: Words are runs of digits, letters and all characters beyond ASCII; A-Z count as a-z.
NOT_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
RAW_GAP = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
BASE = (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl"))

#: Families: label stem, keyword that a text must have, names as patterns over single-spaced words, versions.
FAMILIES = (
    ("gpl", "general public", (r"(?:gnu )?general public licen[sc]e",), ("1 0", "1", "2 0", "2", "3 0", "3")),
    ("gpl", "gpl", (r"(?:gnu )?gpl",), ("1 0", "1", "2 0", "2", "3 0", "3")),
    ("lgpl", "lesser general", (r"(?:gnu )?lesser general public licen[sc]e",), ("2 1", "3 0", "3")),
    ("lgpl", "library general", (r"(?:gnu )?library general public licen[sc]e",), ("2 0", "2")),
    ("lgpl", "lgpl", (r"(?:gnu )?lgpl",), ("2 0", "2", "2 1", "3 0", "3")),
    ("agpl", "affero", (r"(?:gnu )?affero general public licen[sc]e",), ("1 0", "3 0", "3")),
    ("agpl", "agpl", (r"(?:gnu )?agpl",), ("1 0", "3 0", "3")),
    ("gfdl", "free documentation", (r"(?:gnu )?free documentation licen[sc]e",), ("1 1", "1 2", "1 3")),
    ("apache", "apache", (r"apache(?: software)? licen[sc]e",), ("1 0", "1 1", "2 0", "2")),
    ("mpl", "mozilla public", (r"mozilla public licen[sc]e",), ("1 0", "1 1", "2 0")),
    ("epl", "eclipse public", (r"eclipse public licen[sc]e",), ("1 0", "2 0")),
    ("cddl", "common development", (r"common development and distribution licen[sc]e",), ("1 0", "1 1")),
    ("eupl", "european union public", (r"european union public licen[sc]e",), ("1 0", "1 1", "1 2")),
    ("artistic", "artistic", (r"artistic licen[sc]e",), ("1 0", "2 0")),
    ("bsl", "boost", (r"boost software licen[sc]e",), ("1 0",)),
    ("afl", "academic free", (r"academic free licen[sc]e",), ("1 1", "1 2", "2 0", "2 1", "3 0")),
    ("osl", "open software licen", (r"open software licen[sc]e",), ("1 0", "1 1", "2 0", "2 1", "3 0")),
    ("lppl", "latex project", (r"latex project public licen[sc]e",), ("1 0", "1 1", "1 2", "1 3")),
    ("zpl", "zope public", (r"zope public licen[sc]e",), ("1 1", "2 0", "2 1")),
    ("php", "php licen", (r"php licen[sc]e",), ("3 0", "3 01")),
    ("python", "python software foundation", (r"python software foundation licen[sc]e",), ("2 0", "2")),
    ("odbl", "open database", (r"open database licen[sc]e",), ("1 0",)),
    ("cecill", "cecill", (r"cecill(?: free software)?(?: licen[sc]e)?",), ("1 0", "1 1", "2 0", "2 1")),
    ("mspl", "microsoft public", (r"microsoft public licen[sc]e",), ()),
    ("msrl", "microsoft reciprocal", (r"microsoft reciprocal licen[sc]e",), ()),
    ("mit", "mit licen", (r"mit licen[sc]e",), ()),
    ("mit", "expat licen", (r"expat licen[sc]e",), ()),
    ("isc", "isc licen", (r"isc licen[sc]e",), ()),
    ("zlib", "zlib", (r"zlib(?: libpng)? licen[sc]e",), ()),
    ("unlicense", "unlicense", (r"(?:the )?unlicense",), ()),
    ("wtfpl", "wtfpl", (r"wtfpl",), ("1", "2")),
    ("bsd-2-clause", "bsd", (r"(?:simplified bsd|bsd 2 clause|2 clause bsd|two clause bsd|freebsd)(?: licen[sc]e)?",), ()),
    ("bsd-3-clause", "bsd", (r"(?:new bsd|modified bsd|revised bsd|bsd 3 clause|3 clause bsd|three clause bsd)(?: licen[sc]e)?",), ()),
    ("bsd-4-clause", "bsd", (r"(?:original bsd|bsd 4 clause|4 clause bsd|four clause bsd)(?: licen[sc]e)?",), ()),
    ("bsd", "bsd licen", (r"bsd licen[sc]e",), ()),
)
#: Stems whose identifier has other words.
SPDX_NAMES = {"mspl": "ms pl", "msrl": "ms rl"}
#: Creative Commons: the short form's words and the long form's.
CC_PARTS = (("by", "attribution"), ("by-sa", "attribution share ?alike"), ("by-nc", "attribution non ?commercial"), ("by-nd", "attribution no ?deriv(?:ative)?s?(?: works)?"), ("by-nc-sa", "attribution non ?commercial share ?alike"), ("by-nc-nd", "attribution non ?commercial no ?deriv(?:ative)?s?(?: works)?"))
CC_VERSIONS = ("1 0", "2 0", "2 5", "3 0", "4 0")
#: Labels of weak sentences, which stand in many kinds of text.
WEAK = ("proprietary", "cc0", "cc", "non-commercial")


@dataclass(frozen=True)
class Rule:
    """priority: smaller is stronger; confidence: of a detection, 0 to 1. pattern matches whole words; each match has the keyword."""

    name: str
    label: str
    keyword: str
    pattern: str
    priority: int
    confidence: float


def rules() -> list[Rule]:
    """The ordered rules: identifiers, full names with version, sentences, names without version, in this order of priority."""
    out: list[Rule] = []

    def add(label: str, keyword: str, pattern: str, priority: int, confidence: float) -> None:
        out.append(Rule(f"r{len(out):03d}", label, keyword, pattern, priority, confidence))

    for stem, keyword, names, versions in FAMILIES:
        for name in names:
            for v in versions:
                label = f"{stem}-{v.replace(' ', '.')}"
                tail = rf"(?:,? ?v(?:ersion)? ?| ){v}(?! \d)"
                add(f"{label}+", keyword, rf"{name}{tail}(?: of the licen[sc]e)? or (?:at your option )?any later version", 1, 1.0)
                add(label, keyword, rf"{name}{tail}", 2, 0.95)
                add(label, keyword, rf"version {v} of the {name}", 2, 0.95)
            add(stem, keyword, rf"(?:licen[sc]ed|released|distributed|available) under (?:the )?(?:terms of the )?{name}", 4, 0.9)
            add(stem, keyword, name, 5, 0.7 if versions else 0.85)
    for stem, v in dict.fromkeys((f[0], v) for f in FAMILIES for v in (*f[3], "")):
        words = f"{SPDX_NAMES.get(stem, stem.replace('-', ' '))} {v}".strip()
        add(f"{stem}-{v.replace(' ', '.')}" if v else stem, "spdx licen", rf"spdx licen[sc]e identifier {words}(?! \d)(?: only)?", 0, 1.0)
    for short, long in CC_PARTS:
        words = short.replace("-", " ")
        for v in CC_VERSIONS:
            add(f"cc-{short}-{v.replace(' ', '.')}", f"cc {words}", rf"cc {words} {v}", 2, 0.95)
            add(f"cc-{short}-{v.replace(' ', '.')}", "creative commons", rf"creative commons {long} {v}(?: international| unported)?(?: licen[sc]e)?", 2, 0.95)
            add(f"cc-{short}-{v.replace(' ', '.')}", "creativecommons", rf"creativecommons org licenses {words} {v}", 1, 1.0)
        add(f"cc-{short}", f"cc {words}", rf"(?:licen[sc]ed under |licen[sc]e )cc {words}", 4, 0.8)
        add(f"cc-{short}", "creative commons", rf"creative commons {long}(?: licen[sc]e)?", 5, 0.7)
    for label, keyword, pattern in SENTENCES:
        add(label, keyword, pattern, 3, 0.6 if label in WEAK else 0.9)
    return out


def lowered(text: Column) -> Column:
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_words, n_base, first_word, last_word, base_labels, labels, score, detections), a row for each document.

    Base: the places where the words of a phrase of BASE stand one after the other, counted over all phrases, with the
    smallest and largest start. The rules run over the words joined by single spaces, each only where its keyword
    occurs; a detection inside the interval of another one goes unless its priority is stronger (equal intervals: the
    stronger, then the earlier rule stays). labels joins the base labels and those of what stays; detections has them
    as (label, rule, start, end, priority, confidence) by place, in characters of the joined words. score is the
    greatest confidence, base detections counting 0.9; 0 without any.

    Null and empty texts have no words and no labels. Repeated rows give a row each, an empty table none. Texts
    without any keyword of a rule are settled by a substring test; nothing is shuffled. Of a text's detections, all are
    sorted once and passed once.
    """
    every = rules()
    text = F.coalesce(F.col(text_col), F.lit(""))
    hinted = _hinted(F.lower(text), every)
    clean = F.trim(F.regexp_replace(lowered(text), NOT_WORD, " "))
    flat = F.when(hinted, F.concat(F.lit(" "), clean, F.lit(" ")))
    rows = docs.select(F.col(id_col).alias("id"), count_words(text).alias("n_words"), flat.alias("flat"))
    tokens = F.filter(F.split(F.trim("flat"), " "), lambda w: w != "")
    base_hint = F.greatest(*[F.coalesce(F.contains(F.col("flat"), F.lit(f" {p} ")), F.lit(False)) for p, _ in BASE])
    gated = F.flatten(F.transform(F.filter(_table(every), lambda g: F.contains(F.col("flat"), g["keyword"])), lambda g: g["rules"]))
    hits = F.sort_array(F.flatten(F.transform(gated, lambda r: _intervals(F.col("flat"), r))))
    found = rows.withColumns({"tokens": F.when(base_hint, tokens), "hits": F.when(F.col("flat").isNotNull(), hits)})
    starts = [_places(F.col("tokens"), p) for p, _ in BASE]
    places = F.array_sort(F.flatten(F.array(*[F.when(F.coalesce(F.size("tokens"), F.lit(0)) > 0, s).otherwise(F.array().cast("array<int>")) for s in starts])))
    named = F.array(*[F.when(F.contains(F.col("flat"), F.lit(f" {p} ")), F.lit(label)) for p, label in BASE])
    found = found.withColumns({"places": places, "named": F.array_sort(F.array_distinct(F.array_compact(named))), "detections": _outer(F.coalesce("hits", F.array().cast(_HITS)))})
    labels = F.array_sort(F.array_distinct(F.concat("named", F.transform("detections", lambda d: d["label"]))))
    score = F.greatest(F.coalesce(F.array_max(F.transform("detections", lambda d: d["confidence"])), F.lit(0.0)), F.when(F.size("named") > 0, 0.9).otherwise(0.0))
    shown = F.transform("detections", lambda d: F.struct(d["label"].alias("label"), d["rule"].alias("rule"), d["start"].alias("start"), (-d["back"]).alias("end"), d["priority"].alias("priority"), d["confidence"].alias("confidence")))
    return found.select(
        "id", "n_words", F.size("places").cast("long").alias("n_base"),
        F.when(F.size("places") > 0, F.array_min("places")).cast("long").alias("first_word"),
        F.when(F.size("places") > 0, F.array_max("places")).cast("long").alias("last_word"),
        F.array_join("named", ",").alias("base_labels"), F.array_join(labels, ",").alias("labels"), score.alias("score"), shown.alias("detections"),
    )


#: A detection; its natural order is by start, longer first, stronger first, then by rule. back is the end's negative.
_HITS = "array<struct<start:int,back:int,priority:int,rule:string,label:string,confidence:double>>"
#: What marks a match's begin and end; neither occurs in joined words.
_BEGIN, _END = "\x01", "\x02"


def count_words(text: Column) -> Column:
    return F.size(F.array_remove(F.split(text, RAW_GAP), "")).cast("long")


def _table(every: list[Rule]) -> Column:
    """The rules by keyword, as one constant: read from JSON while the query is planned."""
    groups: dict[str, list[dict]] = {}
    for r in every:
        groups.setdefault(r.keyword, []).append({"rule": r.name, "label": r.label, "pattern": rf"(?<= )(?:{r.pattern})(?= )", "priority": r.priority, "confidence": r.confidence})
    kind = "array<struct<keyword:string,rules:array<struct<rule:string,label:string,pattern:string,priority:int,confidence:double>>>>"
    return F.from_json(F.lit(json.dumps([{"keyword": k, "rules": own} for k, own in groups.items()])), kind)


def _folded(items: Column, first: Column, step: Callable[[Column, Column], tuple[Column, Column]]) -> Column:
    """What a pass over an array hands out: step(state, item) gives the next state and an array of hits.

    Arrays grow by copying, so the pass goes by blocks of about the root of the length: n ** 1.5 copies and not n ** 2.
    """
    none = F.array().cast(_HITS)
    width = F.ceil(F.sqrt(F.size(items))).cast("int")
    blocks = F.transform(F.sequence(F.lit(0), F.ceil(F.size(items) / width).cast("int") - 1), lambda b: F.slice(items, b * width + 1, width))

    def one(s: Column, x: Column) -> Column:
        state, out = step(s["state"], x)
        return F.struct(state.alias("state"), F.concat(s["out"], out).alias("out"))

    def block(s: Column, xs: Column) -> Column:
        inner = F.aggregate(xs, F.struct(s["state"].alias("state"), none.alias("out")), one)
        return F.transform(F.array(inner), lambda i: F.struct(i["state"].alias("state"), F.array_append(s["out"], i["out"]).alias("out")))[0]

    start = F.struct(first.alias("state"), F.array().cast(f"array<{_HITS}>").alias("out"))
    return F.when(F.size(items) > 0, F.aggregate(blocks, start, block, lambda s: F.flatten(s["out"]))).otherwise(none)


def _outer(hits: Column) -> Column:
    """Sorted hits without those inside another one of the same or a stronger priority.

    What holds a hit comes before it. The state has for each priority the furthest end of the hits of it or a stronger.
    """

    def step(ends: Column, hit: Column) -> tuple[Column, Column]:
        end = -hit["back"]
        inside = F.get(ends, hit["priority"]) >= end
        after = F.transform(ends, lambda x, k: F.when(k >= hit["priority"], F.greatest(x, end)).otherwise(x))
        return after, F.when(inside, F.array().cast(_HITS)).otherwise(F.array(hit))

    return _folded(hits, F.array(*[F.lit(-1)] * 6), step)


def hint_of(rule: Rule) -> str:
    """A literal that every match has: the stem of `licence` where the pattern can't do without, else its longest word."""
    needed, before = rule.pattern, ""
    while needed != before:  # optional groups and groups of alternatives, from the inside out
        needed, before = re.sub(r"\(\?:[^()]*\)\?|\(\?:[^()]*\|[^()]*\)|\(\?![^()]*\)", " ", needed), needed
    words = re.findall(r"[^\W_]+", re.sub(r"\w\?|\[[^]]*\]|\{[^}]*\}", " ", needed))
    return "licen" if "licen" in needed else max([*words, *rule.keyword.split(" ")], key=len)


def _hinted(low: Column, every: list[Rule]) -> Column:
    """Whether a lower-cased text may hold a match; short words count only where they stand alone."""
    found = {hint_of(r) for r in every} | {"license"}
    own = sorted(w for w in found if not any(v != w and v in w for v in found if len(v) > 2))
    tests = [F.contains(low, F.lit(w)) if len(w) > 2 else F.rlike(low, F.lit(f"(?<![a-z0-9]){w}(?![a-z0-9])")) for w in sorted(own, key=len, reverse=True)]
    return reduce(lambda a, b: a | b, tests)


def _places(tokens: Column, phrase: str) -> Column:
    words = phrase.split(" ")
    return F.filter(F.sequence(F.lit(0), F.size(tokens) - 1), lambda k: _stands(tokens, k, words))


def _stands(tokens: Column, at: Column, words: list[str]) -> Column:
    same = None
    for k, w in enumerate(words):
        one = F.coalesce(F.get(tokens, at + k) == w, F.lit(False))
        same = one if same is None else same & one
    return same


def _intervals(text: Column, rule: Column) -> Column:
    """All matches of the rule with their places: each is marked, and the text cut before the marks."""
    pieces = F.split(F.regexp_replace(text, rule["pattern"], F.lit(f"{_BEGIN}$0{_END}")), _BEGIN)

    def step(at: Column, piece: Column) -> tuple[Column, Column]:
        length = F.instr(piece, F.lit(_END)) - 1
        hit = F.struct(at.alias("start"), (-(at + length)).alias("back"), rule["priority"].alias("priority"), rule["rule"].alias("rule"), rule["label"].alias("label"), rule["confidence"].alias("confidence"))
        return at + F.length(piece) - 1, F.array(hit)

    return F.transform(F.array(pieces), lambda p: F.when(F.size(p) > 1, _folded(F.slice(p, F.lit(2), F.size(p)), F.length(p[0]), step)).otherwise(F.array().cast(_HITS)))[0]
