"""License detection by ordered signature rules, in DataFrame functions only.

Texts are lower-cased (A-Z only) and reduced to words; a document that holds none of the
gate keywords is done after the word count. For the others, each rule whose keyword the text
holds is matched; the rules are built from families of hand-written patterns. A detection
is suppressed if its words lie within those of a detection of higher priority (or of equal priority, when it is
shorter). Base phrases are always kept.

Null and empty texts have no words and no detection; the score is then 0. Each input row
gives one result row, also when rows or ids repeat or are null.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import product

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

NOT_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
MARK = "\x01"  # no word holds it
FOUND = "struct<first:int,back:int,rank:int,rule:int,label:string,weight:double>"
# Phrases that the base detection reports, with their labels
BASE = (("gnu general public license", "gpl"), ("apache license", "apache"), ("cc by", "cc-by"), ("mit license", "mit"))
# Any rule's text holds one of these, so a text without them is skipped
GATES = ("licen", "cc by", "cc0", "public domain", "copyright", "spdx", "gpl", "warranty", "permission", "redistribution", "creativecommons", "creative commons", "wtfpl", "gfdl", "bsd")


@dataclass(frozen=True)
class Rule:
    """``pattern`` matches whole words of the reduced text; ``keyword`` must occur for it to be tried."""

    label: str
    priority: int
    keyword: str
    pattern: str
    weight: float


def rules() -> list[Rule]:
    """The ordered rules: exact notices first (priority 3), named versions (2), names (1)."""
    found: list[Rule] = []

    def add(priority: int, weight: float, label: str, keyword: str, *patterns: str) -> None:
        found.extend(Rule(label, priority, keyword, p, weight) for p in patterns)

    numbers = {"1": "1(?: 0)?", "1.1": "1 1", "2": "2(?: 0)?", "2.1": "2 1", "3": "3(?: 0)?", "4": "4(?: 0)?"}
    ver = "(?:v|version |ver |v )?"
    gnu = {"gpl": "(?:gnu )?general public licen[sc]e", "lgpl": "(?:gnu )?(?:lesser|library) general public licen[sc]e", "agpl": "(?:gnu )?affero general public licen[sc]e", "gfdl": "(?:gnu )?free documentation licen[sc]e"}
    versions = {"gpl": ("1", "2", "3"), "lgpl": ("2", "2.1", "3"), "agpl": ("1", "3"), "gfdl": ("1.1", "3")}
    for name, long in gnu.items():
        add(1, 0.8, name, "licen", long)
        for v in versions[name]:
            n = numbers[v]
            add(2, 0.9, f"{name}-{v}", "licen", f"{long} {ver}{n}", f"{long} as published by the free software foundation either {ver}{n}", f"{ver}{n} of the {long}", f"{long} {ver}{n} only")
            add(3, 0.95, f"{name}-{v}-or-later", "licen", f"{long} {ver}{n} or (?:any )?later(?: version)?", f"{long} as published by the free software foundation either {ver}{n} of the licen[sc]e or at your option any later version")
            add(2, 0.85, f"{name}-{v}", name, f"(?:gnu )?{name} ?{ver}{n}")
            add(3, 0.9, f"{name}-{v}-or-later", "spdx", f"spdx license identifier {name} {n} or later")
            add(3, 0.9, f"{name}-{v}", "spdx", f"spdx license identifier {name} {n}(?: only)?")
    cc = {"cc-by": "by", "cc-by-sa": "by sa", "cc-by-nc": "by nc", "cc-by-nd": "by nd", "cc-by-nc-sa": "by nc sa", "cc-by-nc-nd": "by nc nd"}
    words = {"by": "attribution", "sa": "share ?alike", "nc": "non ?commercial", "nd": "no ?deriv(?:ative|ative works|s)"}
    for (name, short), (v, n) in product(cc.items(), {"1.0": "1 0", "2.0": "2 0", "2.5": "2 5", "3.0": "3 0", "4.0": "4 0"}.items()):
        long = " ".join(words[x] for x in short.split())
        add(2, 0.9, f"{name}-{v}", "cc", f"cc {short} {n}")
        add(2, 0.9, f"{name}-{v}", "creative commons", f"creative commons {long} {n}(?: international| generic| unported)?(?: licen[sc]e)?")
        add(3, 0.95, f"{name}-{v}", "creativecommons", f"creativecommons org licenses {short} {n}")
    for name, short in cc.items():
        long = " ".join(words[x] for x in short.split())
        add(1, 0.75, name, "creative commons", f"creative commons {long}(?: licen[sc]e)?")
        if name != "cc-by":
            add(1, 0.75, name, "cc by", f"cc {short}")
    add(2, 0.9, "cc0-1.0", "cc0", "cc0 1 0(?: universal)?", "cc0 licen[sc]e", "cc0 public domain dedication")
    add(2, 0.8, "public-domain", "public domain", "(?:released|dedicated|placed) (?:in)?to the public domain", "public domain dedication")
    named = {
        "apache": ("apache(?: software)? licen[sc]e", ("1", "1.1", "2")), "mpl": ("mozilla public licen[sc]e", ("1", "1.1", "2")), "epl": ("eclipse public licen[sc]e", ("1", "2")),
        "cddl": ("common development and distribution licen[sc]e", ("1", "1.1")), "eupl": ("european union public licen[sc]e", ("1", "1.1")), "artistic": ("artistic licen[sc]e", ("1", "2")),
        "osl": ("open software licen[sc]e", ("1", "2", "2.1", "3")), "afl": ("academic free licen[sc]e", ("1.1", "2", "2.1", "3")), "bsl": ("boost software licen[sc]e", ("1",)),
        "cpl": ("common public licen[sc]e", ("1",)), "ofl": ("open font licen[sc]e", ("1", "1.1")), "lppl": ("latex project public licen[sc]e", ("1", "1.1")), "zpl": ("zope public licen[sc]e", ("1.1", "2", "2.1")),
        "psf": ("python software foundation licen[sc]e", ("2",)), "odbl": ("open database licen[sc]e", ("1",)), "upl": ("universal permissive licen[sc]e", ("1",)), "unicode": ("unicode licen[sc]e", ("3",)),
    }
    for name, (long, vs) in named.items():
        add(1, 0.8, name, "licen", long)
        for v in vs:
            add(2, 0.9, f"{name}-{v}", "licen", f"{long} {ver}{numbers[v]}", f"{ver}{numbers[v]} of the {long}")
            add(3, 0.9, f"{name}-{v}", "spdx", f"spdx license identifier {name} {numbers[v]}")
    for name, pattern in {"mit": "mit licen[sc]e", "isc": "isc licen[sc]e", "zlib": "zlib licen[sc]e", "x11": "x11 licen[sc]e", "wtfpl": "wtfpl", "unlicense": "the unlicen[sc]e", "ncsa": "ncsa open source licen[sc]e", "postgresql": "postgresql licen[sc]e", "beerware": "beer ware licen[sc]e", "json": "json licen[sc]e", "php": "php licen[sc]e", "ruby": "ruby licen[sc]e", "bsd": "bsd(?: style)? licen[sc]e"}.items():
        own = "wtfpl" if name == "wtfpl" else "licen"
        add(1, 0.8, name, own, pattern, f"(?:under|with) (?:the )?(?:terms of the )?{pattern}", f"licen[sc]ed under (?:the )?{pattern}")
        add(3, 0.9, name, "spdx", f"spdx license identifier {name}")
    for n, spelled in (("2", "(?:2|two)"), ("3", "(?:3|three)"), ("4", "(?:4|four)")):
        add(2, 0.9, f"bsd-{n}", "licen", f"(?:bsd )?{spelled} clause(?: bsd)? licen[sc]e")
        add(2, 0.9, f"bsd-{n}", "bsd", f"bsd {spelled} clause(?: licen[sc]e)?")
    add(3, 0.95, "mit", "permission", "permission is hereby granted free of charge to any person obtaining a copy of this software")
    add(3, 0.95, "isc", "permission", "permission to use copy modify and or distribute this software for any purpose")
    add(3, 0.95, "bsd", "redistribution", "redistribution and use in source and binary forms with or without modification are permitted")
    add(3, 0.9, "proprietary", "copyright", "copyright .{0,60}all rights reserved")
    add(1, 0.5, "no-warranty", "warranty", "without (?:any )?warranty(?: of any kind)?", "as is without warranty")
    return found


def _spaced(text: Column) -> Column:
    """Words between single spaces, one also at either end."""
    return F.concat(F.lit(" "), F.trim(F.regexp_replace(text, NOT_WORD, " ")), F.lit(" "))


def _words_in(text: Column) -> Column:
    return F.length(text) - F.length(F.replace(text, F.lit(" "), F.lit("")))


def detect_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rule_set: list[Rule] | None = None) -> DataFrame:
    """``doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, detections``.

    ``detections``: array of (label, priority, first word, end word) after suppression."""
    own = rules() if rule_set is None else rule_set
    low = F.translate(F.coalesce(F.col(text_col), F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    d = docs.select(F.col(id_col).alias("doc_id"), low.alias("low"))
    gate = F.lit(False)
    # a gate may be split by other separators than spaces: its first word is tested
    for first in sorted({g.split()[0] for g in GATES} | {p.split()[0] for p, _ in BASE}):
        gate = gate | F.contains("low", F.lit(first))
    d = d.select("doc_id", F.regexp_count("low", F.lit(WORD)).cast("bigint").alias("n_words"), F.when(gate, _spaced(F.col("low"))).alias("words"))
    d = d.withColumn("words", F.when(F.rlike(F.col("words"), F.lit("|".join([*GATES, *(f" {p} " for p, _ in BASE)]))), F.col("words")))
    table = F.array(*[F.struct(F.lit(n).alias("rule"), F.lit(r.label).alias("label"), F.lit(r.priority).alias("priority"), F.lit(r.keyword).alias("keyword"), F.lit(rf"(?<= ){r.pattern}(?= )").alias("pattern"), F.lit(r.weight).alias("weight")) for n, r in enumerate(own)])
    base_rows = [F.struct(F.lit(-1 - n).alias("rule"), F.lit(label).alias("label"), F.lit(9).alias("priority"), F.lit(phrase).alias("keyword"), F.lit(rf"(?<= ){phrase}(?= )").alias("pattern"), F.lit(1.0).alias("weight")) for n, (phrase, label) in enumerate(BASE)]
    table = F.concat(F.array(*base_rows), table) if own else F.array(*base_rows)
    gated = F.filter(table, lambda r: F.contains(F.col("words"), r["keyword"]))

    # each rule is tried once; only where it matches, its matches are marked in the text to find their words
    tried = F.transform(gated, lambda r: F.struct(*[r[n].alias(n) for n in ("rule", "label", "priority", "weight", "pattern")], F.regexp_extract_all("words", r["pattern"], F.lit(0)).alias("hits")))
    matched = F.filter(tried, lambda r: F.size(r["hits"]) > 0)

    def places(r: Column) -> Column:
        """Detections of a rule: their first words, and they, in words."""
        marked = F.split(F.trim(F.regexp_replace("words", r["pattern"], F.lit(MARK + "$0"))), " ")
        numbered = F.transform(marked, lambda w, i: F.struct(F.startswith(w, F.lit(MARK)).alias("hit"), i.alias("first")))
        both = F.arrays_zip(F.filter(numbered, lambda w: w["hit"]).alias("at"), r["hits"].alias("hit"))
        first = lambda x: x["at"]["first"]
        return F.transform(both, lambda x: F.struct(first(x).alias("first"), (-first(x) - _words_in(x["hit"]) - 1).alias("back"), (-r["priority"]).alias("rank"), r["rule"].alias("rule"), r["label"].alias("label"), r["weight"].alias("weight")))

    none = F.array().cast(f"array<{FOUND}>")
    flat = F.when(F.col("words").isNotNull(), F.flatten(F.transform(matched, places))).otherwise(none)
    d = d.select("doc_id", "n_words", F.array_sort(flat).alias("found"))

    # sorted by start and falling end: a detection lies within an earlier one if that ends no sooner. The fold writes a
    # letter for each detection, which costs a byte to copy, not a row
    start = F.struct(*[F.lit(0).alias(f"reach{p}") for p in (9, 3, 2, 1)], F.lit("").alias("kept"))

    def step(acc: Column, x: Column) -> Column:
        end, rank = -x["back"], -x["rank"]
        inside = F.lit(False)
        for p in (9, 3, 2, 1):
            inside = inside | ((F.lit(p) >= rank) & (acc[f"reach{p}"] >= end))
        reach = [F.greatest(acc[f"reach{p}"], F.when(rank == p, end).otherwise(F.lit(0))).alias(f"reach{p}") for p in (9, 3, 2, 1)]
        return F.struct(*reach, F.concat(acc["kept"], F.when(inside & (x["rule"] >= 0), "n").otherwise("y")).alias("kept"))

    letters = F.split(F.aggregate("found", start, step, lambda acc: acc["kept"]), "")
    both = F.arrays_zip(F.col("found").alias("x"), letters.alias("kept"))
    d = d.withColumn("kept", F.transform(F.filter(both, lambda z: z["kept"] == "y"), lambda z: z["x"]))
    base = F.filter("kept", lambda x: x["rule"] < 0)
    d = d.withColumn("base", base)
    names = lambda c: F.array_join(F.array_sort(F.array_distinct(F.transform(c, lambda x: x["label"]))), ",")
    firsts = F.transform("base", lambda x: x["first"])
    return d.select(
        "doc_id", "n_words", F.size("base").cast("bigint").alias("n_base"),
        F.array_min(firsts).cast("bigint").alias("first_word"), F.array_max(firsts).cast("bigint").alias("last_word"),
        names("base").alias("base_labels"), names("kept").alias("labels"),
        F.coalesce(F.array_max(F.transform("kept", lambda x: x["weight"])), F.lit(0.0)).alias("score"),
        F.transform("kept", lambda x: F.struct(x["label"].alias("label"), (-x["rank"]).alias("priority"), x["first"].alias("first"), (-x["back"]).alias("end"))).alias("detections"),
    )
