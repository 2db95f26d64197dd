"""License scans: ordered signature rules behind a keyword prefilter.

A text's words are runs of a-z, 0-9 and non-ASCII characters after A-Z are lower-cased. Texts that hold no keyword
of any rule only have their words counted. In the others the words are joined by single spaces, the keywords that
occur select the rules, and each selected rule's regular expression gives detections as intervals of words. The
detections are put in order by start, then by length, then by the rules' priority, and one that lies inside an
earlier one is suppressed: the most specific notice keeps its place, and of rules that fit the same words the first.
The base phrases keep their labels whether or not another detection covers them.

The score is d / (d + 1) for d detections left.

Defined results: null counts as empty; without a detection labels are empty strings and the score is 0; texts of any
length are scanned whole; repeated rows are scanned each; an empty table gives an empty result; other columns of the
input are ignored, whatever their names.
"""

from __future__ import annotations

import json
from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import filled
from .url_filter import LOWER, UPPER

#: Base phrases and their labels, as the contract states them.
BASE = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}

_V = r"(?: version| v)?"
_PUBLIC = "(?:general )?public licen[sc]e"

#: (label, keyword among the words (or one of its FORMS), signature over words joined by spaces), the more specific ones first.
SIGNATURES = [
    *((f"agpl-{n}.0", "affero", rf"(?:gnu )?affero {_PUBLIC}{_V} {n}(?: 0)?(?: or (?:any )?later(?: version)?)?") for n in (1, 2, 3)),
    ("agpl", "affero", rf"(?:gnu )?affero {_PUBLIC}"),
    ("agpl-3.0", "agpl", r"agpl ?v?3(?: 0)?(?: only| or later)?"),
    *((f"lgpl-{n}", "lesser", rf"(?:gnu )?lesser {_PUBLIC}{_V} {n.replace('.', '(?: ')}{')?' if '.' in n else ''}") for n in ("2.1", "3.0")),
    ("lgpl-2.0", "library", rf"(?:gnu )?library {_PUBLIC}{_V} 2(?: 0)?"),
    ("lgpl", "lesser", rf"(?:gnu )?lesser {_PUBLIC}"),
    *((f"lgpl-{n}", "lgpl", rf"lgpl{_V} ?v?{n.replace('.', ' ')}(?: only| or later)?") for n in ("2.1", "3.0")),
    *((f"gpl-{n}.0-or-later", "gnu", rf"(?:the )?gnu {_PUBLIC}{_V} {n}(?: 0)?(?: of the licen[sc]e)? or (?:at your option )?(?:any )?later(?: version)?") for n in (1, 2, 3)),
    *((f"gpl-{n}.0", "gnu", rf"(?:the )?gnu {_PUBLIC}{_V} {n}(?: 0)?(?: only)?") for n in (1, 2, 3)),
    *((f"gpl-{n}.0", "gpl", rf"(?:gnu )?gpl{_V} ?v?{n}(?: 0)?(?: only| or later)?") for n in (1, 2, 3)),
    *((f"gpl-{n}.0", f"gplv{n}", rf"(?:gnu )?gplv{n}") for n in (1, 2, 3)),
    ("gpl", "gnu", rf"(?:the )?gnu {_PUBLIC}"),
    *((f"gfdl-{n}", "documentation", rf"(?:gnu )?free documentation licen[sc]e{_V} {n.replace('.', ' ')}") for n in ("1.1", "1.2", "1.3")),
    ("gfdl", "documentation", r"(?:gnu )?free documentation licen[sc]e"),
    *((f"apache-{n}", "apache", rf"(?:the )?apache (?:software )?licen[sc]e{_V} {n.replace('.', '(?: ')})?") for n in ("1.0", "1.1", "2.0")),
    *((f"apache-{n}", "apache", rf"apache {n.replace('.', ' ')} licen[sc]e") for n in ("1.0", "1.1", "2.0")),
    ("apache", "apache", r"(?:the )?apache (?:software )?licen[sc]e"),
    *((f"bsd-{n}-clause", "bsd", rf"(?:the )?(?:{w}|{n}) clause bsd licen[sc]e") for n, w in ((0, "zero"), (1, "one"), (2, "two"), (3, "three"), (4, "four"))),
    *((f"bsd-{n}-clause", "bsd", rf"bsd {n} clause licen[sc]e") for n in range(5)),
    ("bsd-2-clause", "freebsd", r"freebsd licen[sc]e"),
    *(("bsd-3-clause", "bsd", rf"(?:{w}) bsd licen[sc]e") for w in ("new", "modified", "revised")),
    ("bsd-2-clause", "bsd", r"simplified bsd licen[sc]e"),
    ("bsd", "bsd", r"(?:the )?bsd (?:style )?licen[sc]e"),
    ("mit-0", "mit", r"mit no attribution(?: licen[sc]e)?"),
    ("mit", "mit", r"(?:the )?(?:terms of the )?mit(?: x11)? licen[sc]e"),
    ("mit", "expat", r"expat licen[sc]e"),
    ("x11", "x11", r"x11 licen[sc]e"),
    ("mit", "permission", r"permission is hereby granted free of charge to any person obtaining a copy"),
    ("isc", "permission", r"permission to use copy modify and or distribute this software for any purpose"),
    ("bsd", "redistribution", r"redistribution and use in source and binary forms with or without modification are permitted"),
    ("isc", "isc", r"isc licen[sc]e"),
    *((f"mpl-{n}", "mozilla", rf"mozilla public licen[sc]e{_V} {n.replace('.', ' ')}") for n in ("1.0", "1.1", "2.0")),
    *((f"mpl-{n}", "mpl", rf"mpl{_V} {n.replace('.', ' ')} licen[sc]e") for n in ("1.0", "1.1", "2.0")),
    ("mpl", "mozilla", r"mozilla public licen[sc]e"),
    *((f"epl-{n}", "eclipse", rf"eclipse public licen[sc]e{_V} {n.replace('.', ' ')}") for n in ("1.0", "2.0")),
    ("epl", "eclipse", r"eclipse public licen[sc]e"),
    *((f"eupl-{n}", "european", rf"european union public licen[sc]e{_V} {n.replace('.', ' ')}") for n in ("1.0", "1.1", "1.2")),
    ("eupl", "european", r"european union public licen[sc]e"),
    *((f"cddl-{n}", "cddl", rf"cddl{_V} {n.replace('.', ' ')} licen[sc]e") for n in ("1.0", "1.1")),
    ("cddl", "distribution", r"common development and distribution licen[sc]e"),
    *((f"cc-{p.replace(' ', '-')}-{n}", "cc", rf"cc {p} {n.replace('.', ' ')}(?: international| unported| igo)?") for p in ("by nc nd", "by nc sa", "by nc", "by nd", "by sa", "by") for n in ("1.0", "2.0", "2.5", "3.0", "4.0")),
    *((f"cc-{p.replace(' ', '-')}", "cc", rf"cc {p}") for p in ("by nc nd", "by nc sa", "by nc", "by nd", "by sa", "by")),
    *(
        (f"cc-{p}-{n}", "creative", rf"creative commons {w}{_V} {n.replace('.', ' ')}(?: international| unported)?(?: public)?(?: licen[sc]e)?")
        for p, w in (("by-nc-nd", "attribution non ?commercial no ?deriv(?:ative)?s"), ("by-nc-sa", "attribution non ?commercial share ?alike"), ("by-nc", "attribution non ?commercial"), ("by-nd", "attribution no ?deriv(?:ative)?s"), ("by-sa", "attribution share ?alike"), ("by", "attribution"))
        for n in ("2.0", "2.5", "3.0", "4.0")
    ),
    *((f"cc-{p}", "creative", rf"creative commons {w}(?: licen[sc]e)?") for p, w in (("by-sa", "attribution share ?alike"), ("by-nc", "attribution non ?commercial"), ("by", "attribution"))),
    ("cc0-1.0", "cc0", r"cc0(?: 1 0)?(?: universal)?"),
    ("cc0-1.0", "creative", r"creative commons zero(?: v?1 0)?"),
    ("creative-commons", "creative", r"creative commons(?: licen[sc]e)?"),
    ("unlicense", "unlicense", r"(?:the )?unlicense"),
    ("public-domain", "domain", r"(?:released|dedicated|placed|is) (?:in|into|to) the public domain"),
    ("wtfpl", "wtfpl", r"wtfpl licen[sc]e"),
    ("zlib", "zlib", r"zlib(?: libpng)? licen[sc]e"),
    ("bsl-1.0", "boost", r"boost software licen[sc]e(?:(?: version)? 1 0)?"),
    ("bsl-1.1", "business", r"business source licen[sc]e(?: 1 1)?"),
    *((f"artistic-{n}", "artistic", rf"artistic licen[sc]e{_V} {n.replace('.', ' ')}") for n in ("1.0", "2.0")),
    ("artistic", "artistic", r"(?:perl )?artistic licen[sc]e"),
    *((f"osl-{n}", "open", rf"open software licen[sc]e{_V} {n.replace('.', ' ')}") for n in ("1.0", "2.0", "2.1", "3.0")),
    *((f"afl-{n}", "academic", rf"academic free licen[sc]e{_V} {n.replace('.', ' ')}") for n in ("1.1", "1.2", "2.0", "2.1", "3.0")),
    ("ofl-1.1", "font", r"(?:sil )?open font licen[sc]e(?:(?: version)? 1 1)?"),
    ("odbl-1.0", "database", r"open (?:data commons open )?database licen[sc]e(?: v?1 0)?"),
    ("odc-by-1.0", "commons", r"open data commons attribution licen[sc]e"),
    ("pddl-1.0", "commons", r"(?:open data commons )?public domain dedication and licen[sc]e"),
    ("ms-pl", "microsoft", r"microsoft public licen[sc]e"),
    ("ms-rl", "microsoft", r"microsoft reciprocal licen[sc]e"),
    ("python-2.0", "python", r"python (?:software foundation )?licen[sc]e(?: 2 0)?"),
    ("php-3.01", "php", r"php licen[sc]e(?: version)? 3 01"),
    ("ruby", "ruby", r"ruby licen[sc]e"),
    ("postgresql", "postgresql", r"postgresql licen[sc]e"),
    ("openssl", "openssl", r"openssl licen[sc]e"),
    ("ncsa", "illinois", r"university of illinois ncsa open source licen[sc]e"),
    ("upl-1.0", "universal", r"universal permissive licen[sc]e"),
    ("vim", "vim", r"vim licen[sc]e"),
    ("beerware", "beer", r"beer ?ware licen[sc]e"),
    ("ecl-2.0", "educational", r"educational community licen[sc]e"),
    ("w3c", "w3c", r"w3c software (?:notice and )?licen[sc]e"),
    ("sspl-1.0", "server", r"server side public licen[sc]e"),
    ("elastic-2.0", "elastic", r"elastic licen[sc]e(?: 2 0)?"),
    ("openrail", "openrail", r"(?:creativeml )?openrail(?: m)? licen[sc]e"),
    ("cecill-2.1", "cecill", r"cecill(?: free software)? licen[sc]e(?: agreement)?(?: version)?(?: 2 1)?"),
    ("mulan-psl-2.0", "mulan", r"mulan (?:permissive software|psl) licen[sc]e(?: v?2)?"),
    *(
        (spdx.lower(), "spdx", "spdx licen[sc]e identifier " + " ".join(spdx.lower().replace(".", "-").split("-")))
        for spdx in "GPL-2.0-only GPL-2.0-or-later GPL-3.0-only GPL-3.0-or-later LGPL-2.1-only LGPL-2.1-or-later LGPL-3.0-only LGPL-3.0-or-later AGPL-3.0-only AGPL-3.0-or-later Apache-2.0 MIT MIT-0 BSD-2-Clause BSD-3-Clause ISC MPL-2.0 EPL-2.0 CC0-1.0 CC-BY-4.0 CC-BY-SA-4.0 Unlicense Zlib BSL-1.0 OFL-1.1 EUPL-1.2 WTFPL 0BSD".split()
    ),
    *((f"proprietary-{w}", "rights", rf"(?:{w}) all rights reserved") for w in ("confidential", "proprietary", "internal")),
    ("all-rights-reserved", "rights", r"all rights reserved"),
]

#: Whole words by which the signatures of a keyword may show where they allow it glued on or leave it out.
FORMS = {
    "agpl": ("agpl", "agpl3", "agplv3"),
    "lgpl": ("lgpl", "lgpl2", "lgplv2", "lgpl3", "lgplv3"),
    "gpl": ("gpl", "gpl1", "gplv1", "gpl2", "gplv2", "gpl3", "gplv3"),
    "commons": ("commons", "dedication"),
    "beer": ("beer", "beerware"),
}

EVIDENCE = ("licen", "gpl", "rights", "permission", "redistribution", "commons", "domain", "attribution")
CC = r"cc(?:[\x00-\x2F\x3A-\x60\x7B-\x7F]+by|0)"
OUTSIDE = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"  # between words before A-Z are lower-cased
BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
RULE = "struct<priority: int, label: string, pattern: string>"
PLACES = "array<struct<start: int, size: int, priority: int, label: string>>"


def gate(lowered: Column) -> Column:
    """Whether a lower-case text may match: all signatures hold one of these pieces of words, or "cc" before "by" or "0"."""
    pieces = reduce(or_, (F.contains(lowered, F.lit(x)) for x in EVIDENCE))
    return pieces | (F.contains(lowered, F.lit("cc")) & F.regexp_like(lowered, F.lit(CC)))


def joined_words(text: Column) -> Column:
    """The words with a single space before and behind each."""
    return F.concat(F.lit(" "), F.trim(F.regexp_replace(F.translate(text, UPPER, LOWER), BETWEEN, " ")), F.lit(" "))


def _spaces(text: Column) -> Column:
    return F.length(text) - F.length(F.replace(text, F.lit(" "), F.lit("")))


def _aligned(pattern: Column | str) -> Column:
    return F.concat(F.lit("(?<= )(?:"), F.lit(pattern) if isinstance(pattern, str) else pattern, F.lit(")(?= )"))


def _base(words: Column) -> list[Column]:
    """For each base phrase: a struct of its places, its first and its last word, and its label."""
    out = []
    for phrase, label in BASE.items():
        parts = F.split(words, f"(?<= ){phrase}(?= )", -1)
        n = F.size(parts) - 1
        last = _spaces(words) - _spaces(F.element_at(parts, -1)) - len(phrase.split())
        out.append(F.struct(n.alias("n"), F.when(n > 0, _spaces(parts[0]) - 1).alias("first"), F.when(n > 0, last).alias("last"), F.when(n > 0, F.lit(label)).alias("label")))
    return out


def _places(words: Column, rule: Column) -> Column:
    """Detections of one rule as intervals of words."""
    pattern = _aligned(rule.pattern)
    hits = F.regexp_extract_all(words, pattern, F.lit(0))
    gaps = F.split(words, pattern, -1)
    pairs = F.zip_with(hits, F.slice(gaps, 1, F.size(hits)), lambda h, g: F.struct(_spaces(h).alias("inside"), _spaces(g).alias("before")))
    nothing = F.from_json(F.lit('{"at": -1, "places": []}'), f"struct<at: int, places: {PLACES}>")

    def step(state: Column, x: Column) -> Column:
        start = state.at + x.before
        place = F.struct(start.alias("start"), (x.inside + 1).alias("size"), rule.priority.alias("priority"), rule.label.alias("label"))
        return F.struct((start + x.inside).alias("at"), F.concat(state.places, F.array(place)).alias("places"))

    return F.when(F.size(hits) > 0, F.aggregate(pairs, nothing, step, lambda s: s.places)).otherwise(F.from_json(F.lit("[]"), PLACES))


def _unsuppressed(places: Column) -> Column:
    """Places that lie inside no place before them, in order of start, falling size and priority."""
    order = F.transform(places, lambda p: F.struct(p.start.alias("start"), (-p["size"]).alias("minus"), p.priority.alias("priority"), p.label.alias("label")))
    nothing = F.from_json(F.lit('{"reach": -1, "labels": [], "n": 0}'), "struct<reach: int, labels: array<string>, n: int>")

    def step(state: Column, p: Column) -> Column:
        end = p.start - p.minus
        fresh = end > state.reach
        return F.struct(
            F.greatest(end, state.reach).alias("reach"),
            F.when(fresh, F.array_union(state.labels, F.array(p.label))).otherwise(state.labels).alias("labels"),
            (state.n + fresh.cast("int")).alias("n"),
        )

    return F.aggregate(F.array_sort(order), nothing, step)


def scan(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", signatures: list = SIGNATURES) -> DataFrame:
    """One row per row of docs: its words, base places, labels and score."""
    filed: dict[str, list[dict]] = {}
    for k, (label, word, pattern) in enumerate(signatures):
        for form in FORMS.get(word, (word,)):
            filed.setdefault(form, []).append({"priority": k, "label": label, "pattern": pattern})
    rules = F.from_json(F.lit(json.dumps(filed)), f"map<string, array<{RULE}>>")
    rows = docs.select(F.col(id_column).alias("doc_id"), filled(text_column).alias("text"))
    counted = F.size(F.filter(F.split("text", OUTSIDE), lambda w: w != "")).cast("long")
    rows = rows.select("doc_id", counted.alias("n_words"), "text", F.lower("text").alias("lowered"))
    rows = rows.select("doc_id", "n_words", F.when(gate(F.col("lowered")), joined_words(F.col("text"))).alias("words"))
    words = F.col("words")
    present = F.filter(F.array(*map(F.lit, sorted(filed))), lambda k: F.contains(words, F.concat(F.lit(" "), k, F.lit(" "))))
    selected = F.array_distinct(F.flatten(F.transform(present, lambda k: F.try_element_at(rules, k))))
    held = words.isNotNull()
    kept = _unsuppressed(F.flatten(F.transform(selected, lambda r: _places(words, r))))
    rows = rows.select("doc_id", "n_words", F.when(held, F.struct(F.array(*_base(words)).alias("base"), kept.alias("kept"))).alias("found"))
    base = F.col("found.base")
    base_labels = F.coalesce(F.array_compact(F.transform(base, lambda b: b.label)), F.array().cast("array<string>"))
    more = F.coalesce(F.col("found.kept.labels"), F.array().cast("array<string>"))
    n = F.coalesce(F.col("found.kept.n"), F.lit(0))
    return rows.select(
        "doc_id",
        "n_words",
        F.coalesce(F.aggregate(base, F.lit(0), lambda a, b: a + b.n), F.lit(0)).cast("long").alias("n_base"),
        F.array_min(F.transform(base, lambda b: b.first)).cast("long").alias("first_word"),
        F.array_max(F.transform(base, lambda b: b.last)).cast("long").alias("last_word"),
        F.array_join(F.array_sort(base_labels), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union(base_labels, more)), ",").alias("labels"),
        (n / (n + 1.0)).alias("score"),
    )
