"""License scans by ordered signature rules (operator 5). DataFrame functions only.

Texts become their words, each between two spaces, so that a rule for words in a row
is a pattern without boundaries and a place in words is a count of spaces. Which rules'
keywords are among the words decides which rules run at all (the prefilter). A detection
that lies within one of higher priority, or within a longer one of equal priority, is
suppressed. Three base phrases are counted whatever the rules say.

A null text is empty: no words, no labels, score 0. Null doc_ids stay null; repeated
rows are scanned each. Nothing is shuffled, so no group can be hot.
"""

from __future__ import annotations

from itertools import groupby, product
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corefold.llm.common import text_or_empty

#: Phrases that always count, and their labels.
BASE_PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

BREAKS = "[\\x00-/:-@\\[-`{-\\x7F]+"

#: Label, then names in words (| between alternatives; ? after a word that may lack; # any version number of one or two parts).
FAMILIES = """
mit: mit|expat|x11
apache: apache|apache software foundation
apache-1.1: apache 1 1
apache-2.0: apache 2 0|apache version? 2 0|apache license version 2 0
bsd: bsd|berkeley software distribution
bsd-2-clause: bsd 2 clause|simplified bsd|freebsd
bsd-3-clause: bsd 3 clause|new bsd|modified bsd|revised bsd
bsd-4-clause: bsd 4 clause|original bsd
0bsd: zero clause bsd|0bsd|bsd 0 clause
isc: isc|internet systems consortium
gpl: gpl|gnu gpl|gnu general public
gpl-2.0: gpl v2|gpl 2 0|gplv2|gnu general public license v?? 2
gpl-3.0: gpl v3|gpl 3 0|gplv3|gnu general public license v?? 3
lgpl: lgpl|gnu lgpl|gnu lesser general public|gnu library general public
lgpl-2.1: lgpl v2 1|lgpl 2 1|gnu lesser general public license v?? 2 1
lgpl-3.0: lgpl v3|lgpl 3 0|gnu lesser general public license v?? 3
agpl: agpl|gnu agpl|gnu affero general public|affero general public
agpl-3.0: agpl v3|agpl 3 0|agplv3|gnu affero general public license v?? 3
gfdl: gfdl|gnu fdl|gnu free documentation
mpl: mpl|mozilla public
mpl-1.1: mpl 1 1|mozilla public license v?? 1 1
mpl-2.0: mpl 2 0|mozilla public license v?? 2 0
epl: epl|eclipse public
epl-2.0: epl 2 0|eclipse public license v?? 2 0
cddl: cddl|common development and distribution
cpl: common public
eupl: eupl|european union public
artistic: artistic
artistic-2.0: artistic 2 0|artistic license 2 0
zlib: zlib|zlib libpng
boost: boost|boost software|bsl 1 0
python: psf|python software foundation
php: php
ruby: ruby
openssl: openssl
ofl: ofl|sil open font|open font
unlicense: unlicense
wtfpl: wtfpl|do what the fuck you want to public
cc0: cc0|cc 0|cc zero|creative commons zero
cc: creative commons
cc-by: cc by|creative commons attribution
cc-by-sa: cc by sa|creative commons attribution sharealike|creative commons attribution share alike
cc-by-nc: cc by nc|creative commons attribution noncommercial|creative commons attribution non commercial
cc-by-nd: cc by nd|creative commons attribution noderivatives|creative commons attribution no derivatives|creative commons attribution noderivs
cc-by-nc-sa: cc by nc sa|creative commons attribution noncommercial sharealike|creative commons attribution non commercial share alike
cc-by-nc-nd: cc by nc nd|creative commons attribution noncommercial noderivatives|creative commons attribution non commercial no derivatives
odbl: odbl|open database
odc-by: odc by|open data commons attribution
pddl: pddl|public domain dedication and
ms-pl: ms pl|microsoft public
ms-rl: ms rl|microsoft reciprocal
ncsa: ncsa|university of illinois ncsa
postgresql: postgresql
vim: vim
upl: upl|universal permissive
osl: osl|open software
afl: afl|academic free
blueoak: blue oak model
elastic: elastic
sspl: sspl|server side public
busl: busl|business source
openrail: openrail|open rail
""".strip().splitlines()

#: How a name is put; @ is the name. Priority, words.
FORMS = (
    (3, "spdx license identifier @"),
    (2, "licensed|released|distributed|published|available|provided|covered|offered under|by|with|per the|a? terms? of? the? @ version?? #"),
    (1, "the? @ license|licence v?? #"),
    (1, "license|licence @ v?? #"),
)

#: Signatures without a name. Label, priority, keyword (whole words, one of which stands in every match), words.
NOTICES = (
    ("reserved", 1, "reserved", "all|some|no rights reserved"),
    ("copyright", 1, "copyright", "copyright c? 1|2"),
    ("public-domain", 2, "domain", "in|to|into the public domain"),
    ("public-domain", 1, "domain", "public domain"),
    ("mit", 2, "permission", "permission is hereby granted free of charge to any person obtaining a copy"),
    ("isc", 2, "permission", "permission to use copy modify and or distribute this software for any purpose"),
    ("bsd", 2, "redistribution", "redistribution and use in source and binary forms with or without modification are permitted"),
    ("gpl", 2, "redistribute", "you can redistribute it and or modify it under the terms of the gnu general public license"),
    ("zlib", 2, "implied", "this software is provided as is without any express or implied warranty"),
    ("warranty-disclaimer", 1, "warranty|warranties", "without warranty|warranties of any kind"),
    ("proprietary", 2, "proprietary", "proprietary and confidential"),
    ("proprietary", 2, "permission", "without|prior written|express permission"),
)


class Rule(NamedTuple):
    label: str
    priority: int
    keyword: str
    pattern: str


def pattern(words: str) -> str:
    """A pattern over spaced words from words: | alternatives, ? may lack, ?? may lack and stands for v or version, # a number of one or two parts."""
    out = ""
    for word in words.split():
        if word == "#":
            out += "(?: v?[0-9]+ (?: [0-9]+ )?)?"
        elif word.endswith("??"):
            out += "(?: (?:v|version) )?"
        elif word.endswith("?"):
            out += f"(?: (?:{word[:-1]}) )?"
        elif word == "1|2":
            out += " [12][0-9]{3} "
        else:
            out += f" (?:{word}) " if "|" in word else f" {word} "
    return out


def keyword(name: str) -> str:
    """The longest word that stands wherever the name does, the last of equal ones; "by" only if there is no other."""
    plain = [w for w in name.split() if not w.endswith("?")]
    return max(reversed(plain), key=lambda w: (w != "by", len(w)))


def rules() -> list[Rule]:
    """All signatures, of higher priority first."""
    found = [Rule(label, priority, f" {k} ", pattern(words)) for label, priority, keys, words in NOTICES for k in keys.split("|")]
    for line, (priority, form) in product(FAMILIES, FORMS):
        label, names = line.split(": ")
        for name in names.split("|"):
            if "license" in name.split() and "license|licence" in form:
                continue
            found.append(Rule(label, priority, f" {keyword(name)} ", pattern(form.replace("@", name))))
    names = [(line.split(": ")[0], n) for line in FAMILIES for n in line.split(": ")[1].split("|")]
    # a name of several words stands for itself
    found += [Rule(label, 1, f" {keyword(n)} ", pattern(n)) for label, n in names if len(n.split()) >= 2]
    return sorted(dict.fromkeys(found), key=lambda r: (-r.priority, r.label, r.pattern))


def keywords(signatures: list[Rule]) -> list[str]:
    """Every match of a rule or a base phrase holds one of these words."""
    return sorted({r.keyword.strip() for r in signatures} | {keyword(p) for p in BASE_PHRASES})


def _spaced(words: Column) -> Column:
    return F.when(F.size(words) > 0, F.concat(F.lit(" "), F.array_join(words, "  "), F.lit(" "))).otherwise("")


def _count(text: Column) -> Column:
    """Words in a run of spaced words."""
    return ((F.octet_length(text) - F.octet_length(F.replace(text, F.lit(" "), F.lit("")))) / 2).cast("long")


def scan(docs: DataFrame, signatures: list[Rule] | None = None) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, detections."""
    signatures = rules() if signatures is None else signatures
    # lower() folds other letters too; of those only the Kelvin sign becomes one of a-z (k), which no base phrase has
    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.array_remove(F.split(F.lower(text_or_empty()), BREAKS), "").alias("_w"))
    known = F.array(*[F.lit(k) for k in keywords(signatures)])
    out = out.withColumn("_h", F.array_intersect("_w", known))  # the prefilter: which keywords stand in the text
    out = out.select("doc_id", F.size("_w").cast("long").alias("_n"), "_h", F.when(F.size("_h") > 0, _spaced(F.col("_w"))).otherwise("").alias("_s"))
    # base phrases: the runs of words between their places
    for i, phrase in enumerate(BASE_PHRASES):
        out = out.withColumn(f"_b{i}", F.split("_s", pattern(phrase)))
    size = [F.size(f"_b{i}") - 1 for i in range(len(BASE_PHRASES))]
    first = F.least(*[F.when(n > 0, _count(F.col(f"_b{i}")[0])) for i, n in enumerate(size)])
    last = F.greatest(*[F.when(n > 0, F.col("_n") - _count(F.element_at(f"_b{i}", -1)) - len(p.split())) for i, (n, p) in enumerate(zip(size, BASE_PHRASES, strict=True))])
    base = F.array_compact(F.array(*[F.when(n > 0, F.lit(label)) for n, label in zip(size, BASE_PHRASES.values(), strict=True)]))
    out = out.select("doc_id", F.col("_n").alias("n_words"), sum(size).cast("long").alias("n_base"), first.alias("first_word"), last.alias("last_word"), base.alias("_base"), "_h", "_s")
    ruled = sorted(signatures, key=lambda r: r.keyword)
    of = lambda rs: F.array(*[F.struct(F.lit(r.label).alias("label"), F.lit(r.priority).alias("priority"), F.lit(r.pattern).alias("pattern")) for r in rs])
    table = F.array(*[F.struct(F.lit(k.strip()).alias("keyword"), of(rs).alias("rules")) for k, rs in groupby(ruled, key=lambda r: r.keyword)])

    none = F.array().cast("array<struct<first:long,to:long,rank:int,label:string>>")

    def places(rule: Column) -> Column:
        """(first word, last word, priority, label) of each match of one rule."""
        gaps = F.transform(F.split(F.col("_s"), rule["pattern"]), _count)
        lengths = F.transform(F.regexp_extract_all(F.col("_s"), rule["pattern"], F.lit(0)), _count)
        walk = F.aggregate(
            F.zip_with(gaps, lengths, lambda gap, length: F.struct(gap.alias("gap"), length.alias("length"))),
            F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<first:long,last:long>>").alias("found")),
            lambda acc, x: F.struct(
                (acc["at"] + x["gap"] + F.coalesce(x["length"], F.lit(0))).alias("at"),
                F.when(x["length"].isNull(), acc["found"]).otherwise(F.concat(acc["found"], F.array(F.struct((acc["at"] + x["gap"]).alias("first"), (acc["at"] + x["gap"] + x["length"] - 1).alias("last"))))).alias("found"),
            ),
            lambda acc: acc["found"],
        )
        found = F.transform(walk, lambda p: F.struct(p["first"].alias("first"), (-p["last"]).alias("to"), (-rule["priority"]).alias("rank"), rule["label"].alias("label")))
        return F.when(F.rlike(F.col("_s"), rule["pattern"]), found).otherwise(none)

    run = F.flatten(F.transform(F.filter(table, lambda r: F.array_contains("_h", r["keyword"])), lambda r: r["rules"]))
    found = F.flatten(F.transform(run, places))
    out = out.withColumn("_d", F.when(F.col("_s") == "", none).otherwise(F.sort_array(F.array_distinct(found))))
    # In this order (first word; longer first; higher priority first) whatever holds a detection comes before it.
    zero = F.lit(-1).cast("long")
    start = F.struct(zero.alias("e1"), zero.alias("e2"), zero.alias("e3"), F.array().cast("array<string>").alias("labels"), F.lit(0).alias("n"), F.lit(0).alias("best"))

    def sweep(acc: Column, d: Column) -> Column:
        end, p = -d["to"], -d["rank"]
        held = (acc["e3"] >= end) | ((p <= 2) & (acc["e2"] >= end)) | ((p <= 1) & (acc["e1"] >= end))
        higher = lambda field, level: F.when(p == level, F.greatest(acc[field], end)).otherwise(acc[field]).alias(field)
        return F.struct(
            higher("e1", 1), higher("e2", 2), higher("e3", 3),
            F.when(held, acc["labels"]).otherwise(F.array_union(acc["labels"], F.array(d["label"]))).alias("labels"),
            (acc["n"] + F.when(held, 0).otherwise(1)).alias("n"),
            F.when(held, acc["best"]).otherwise(F.greatest(acc["best"], p)).alias("best"),
        )

    out = out.withColumn("_k", F.aggregate("_d", start, sweep))
    labels = F.sort_array(F.array_union("_base", "_k.labels"))
    score = F.when(F.col("_k.best") == 3, 1.0).when(F.col("_k.best") == 2, 0.9).when(F.col("_k.best") == 1, 0.6).when(F.col("n_base") > 0, 0.5).otherwise(0.0)
    return out.select("doc_id", "n_words", "n_base", "first_word", "last_word", F.array_join(F.sort_array("_base"), ",").alias("base_labels"), F.array_join(labels, ",").alias("labels"), score.alias("score"), F.col("_k.n").cast("long").alias("detections"))
