"""License scan by ordered signature rules, in DataFrame functions only.

A text is gated by cheap substring tests on its lower-case form. Only gated texts are normalised, to words with a space on
either side, and meet the rules: a rule's keyword must occur before its pattern runs. Each match is an interval of words.
An interval inside another of no lower priority is suppressed, and so is the later rule of two that claim the same words.
The base phrases are rules as well, and their labels always stay.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SEPARATOR = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"  # of text whose A-Z are not lowered yet
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

# Base phrases and their labels.
BASE = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}

# Licence names (words, alternatives in brackets) with their labels.
NAMES = {
    "apache": "apache", "apache 2": "apache-2.0", "apache 2 0": "apache-2.0", "mit": "mit", "x11": "x11", "expat": "mit", "isc": "isc", "zlib": "zlib", "libpng": "libpng",
    "bsd": "bsd", "bsd 2 clause": "bsd-2-clause", "bsd 3 clause": "bsd-3-clause", "simplified bsd": "bsd-2-clause", "new bsd": "bsd-3-clause", "zero clause bsd": "0bsd", "0bsd": "0bsd",
    "gpl": "gpl", "gnu gpl": "gpl", "gplv2": "gpl-2.0", "gplv3": "gpl-3.0", "gpl 2 0": "gpl-2.0", "gpl 3 0": "gpl-3.0", "gnu general public": "gpl", "lgpl": "lgpl", "lgpl 2 1": "lgpl-2.1", "lgpl 3 0": "lgpl-3.0",
    "gnu lesser general public": "lgpl", "gnu library general public": "lgpl", "agpl": "agpl", "gnu affero general public": "agpl", "gnu free documentation": "gfdl", "gfdl": "gfdl",
    "mozilla public": "mpl", "mpl 2 0": "mpl-2.0", "eclipse public": "epl", "epl 2 0": "epl-2.0", "common development and distribution": "cddl", "cddl": "cddl", "european union public": "eupl", "eupl": "eupl",
    "artistic": "artistic", "artistic 2 0": "artistic-2.0", "boost software": "bsl-1.0", "academic free": "afl", "open software": "osl", "microsoft public": "ms-pl", "microsoft reciprocal": "ms-rl",
    "python software foundation": "psf", "php": "php", "ruby": "ruby", "perl": "artistic", "unlicense": "unlicense", "wtfpl": "wtfpl", "openssl": "openssl", "postgresql": "postgresql",
    "creative commons": "cc", "creative commons attribution": "cc-by", "cc by": "cc-by", "cc by sa": "cc-by-sa", "cc by nc": "cc-by-nc", "cc by nd": "cc-by-nd", "cc by nc sa": "cc-by-nc-sa", "cc by nc nd": "cc-by-nc-nd",
    "cc0": "cc0", "cc zero": "cc0", "open database": "odbl", "odbl": "odbl", "open data commons": "odc", "open government": "ogl", "sil open font": "ofl", "ofl": "ofl", "open rail": "openrail", "llama community": "llama",
    "business source": "busl", "server side public": "sspl", "elastic": "elastic", "polyform noncommercial": "polyform-nc", "blue oak model": "blueoak", "educational community": "ecl",
}

# How a licence is named in running text; {} is the name. (priority, words)
FORMS = [
    (95, "spdx licen[sc]e identifier {}"),
    (90, "(?:dual )?licen[sc]ed under (?:the )?(?:terms of (?:the )?)?{}(?: licen[sc]e)?(?: (?:version |v)?[0-9]+(?: [0-9]+)?)?"),
    (85, "(?:released|distributed|available|published) under (?:the )?{} licen[sc]e"),
    (80, "{} licen[sc]e(?: version [0-9]+(?: [0-9]+)?)?"),
]

# Rules that stand alone. (priority, label, keyword, words)
ALONE = [
    (70, "cc-by-sa", "cc", "cc by sa(?: [0-9]+ [0-9]+)?"),
    (70, "cc-by-nc", "cc", "cc by nc(?: [0-9]+ [0-9]+)?"),
    (70, "cc-by-nd", "cc", "cc by nd(?: [0-9]+ [0-9]+)?"),
    (75, "cc-by-nc-sa", "cc", "cc by nc sa(?: [0-9]+ [0-9]+)?"),
    (75, "cc-by-nc-nd", "cc", "cc by nc nd(?: [0-9]+ [0-9]+)?"),
    (75, "gpl-2.0-or-later", "later", "version 2 (?:of the licen[sc]e )?or (?:at your option )?any later version"),
    (75, "gpl-3.0-or-later", "later", "version 3 (?:of the licen[sc]e )?or (?:at your option )?any later version"),
    (60, "lgpl", "lesser", "lesser general public licen[sc]e"),
    (60, "agpl", "affero", "affero general public licen[sc]e"),
    (50, "copyright", "copyright", "copyright (?:c )?[0-9]{4}"),
    (50, "proprietary", "licen", "(?:proprietary|commercial) licen[sc]e"),
    (40, "license-mention", "licen", "licen[sc]e agreement"),
]

# Words of licence bodies, notices and reservations. (priority, label, keyword, words); W is any word.
BODIES = [
    (98, "mit", "granted", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    (97, "mit", "granted", "permission is hereby granted free of charge to any person obtaining a copy"),
    (98, "bsl-1.0", "granted", "permission is hereby granted free of charge to any person or organization obtaining a copy"),
    (97, "isc", "permission", "permission to use copy modify and (?:or )?distribute this software for any purpose with or without fee is hereby granted"),
    (90, "hpnd", "permission", "permission to use copy modify and distribute this software and its documentation for any purpose"),
    (85, "mit", "copyright", "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software"),
    (60, "warranty-disclaimer", "warranty", "the software is provided as is without warranty of any kind express or implied"),
    (60, "warranty-disclaimer", "merchantability", "without even the implied warranty of merchantability or fitness for a particular purpose"),
    (60, "warranty-disclaimer", "merchantability", "implied warranties of merchantability(?: and)?(?: fitness for a particular purpose)?"),
    (70, "bsd", "redistribution", "redistribution and use in source and binary forms with or without modification are permitted"),
    (71, "bsd", "redistributions", "redistributions of source code must retain the above copyright notice"),
    (71, "bsd", "redistributions", "redistributions in binary form must reproduce the above copyright notice"),
    (88, "bsd-3-clause", "neither", "neither the name of (?:W ){1,12}(?:nor|or) (?:W ){0,6}may be used to endorse or promote products"),
    (88, "bsd-4-clause", "advertising", "all advertising materials mentioning features or use of this software must display"),
    (65, "bsd", "contributors", "this software is provided by the copyright holders and contributors as is"),
    (90, "zlib", "misrepresented", "the origin of this software must not be misrepresented"),
    (85, "zlib", "liable", "in no event will the authors be held liable for any damages arising from the use of this software"),
    (95, "apache-2.0", "compliance", "you may not use this file except in compliance with the licen[sc]e"),
    (96, "apache-2.0", "apache", "apache org licen[sc]es licen[sc]e 2 0"),
    (90, "apache-2.0", "apache", "licensed to the apache software foundation(?: asf)? under one or more contributor licen[sc]e agreements"),
    (92, "gpl", "redistribute", "this (?:program|software|file|library) is free software you can redistribute it and or modify it under the terms of the gnu general public licen[sc]e"),
    (93, "lgpl", "redistribute", "this (?:program|software|file|library) is free software you can redistribute it and or modify it under the terms of the gnu (?:lesser|library) general public licen[sc]e"),
    (93, "agpl", "redistribute", "this (?:program|software|file|library) is free software you can redistribute it and or modify it under the terms of the gnu affero general public licen[sc]e"),
    (80, "gpl", "gnu", "you should have received a copy of the gnu general public licen[sc]e"),
    (81, "lgpl", "gnu", "you should have received a copy of the gnu (?:lesser|library) general public licen[sc]e"),
    (81, "agpl", "gnu", "you should have received a copy of the gnu affero general public licen[sc]e"),
    (94, "gpl-2.0", "gnu", "gnu general public licen[sc]e version 2(?: june 1991)?"),
    (94, "gpl-3.0", "gnu", "gnu general public licen[sc]e version 3(?: 29 june 2007)?"),
    (94, "lgpl-2.1", "gnu", "gnu lesser general public licen[sc]e version 2 1"),
    (94, "lgpl-3.0", "gnu", "gnu lesser general public licen[sc]e version 3"),
    (94, "agpl-3.0", "gnu", "gnu affero general public licen[sc]e version 3"),
    (75, "gpl", "gnu", "gnu org licen[sc]es gpl"),
    (75, "gfdl", "gnu", "permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation licen[sc]e"),
    (70, "gpl-exception", "exception", "as a special exception (?:W ){1,12}permission to link"),
    (95, "mpl-2.0", "mozilla", "this source code form is subject to the terms of the mozilla public licen[sc]e v 2 0"),
    (85, "mpl", "mozilla", "the contents of this file are subject to the mozilla public licen[sc]e"),
    (95, "epl", "eclipse", "this program and the accompanying materials are made available under the terms of the eclipse public licen[sc]e"),
    (85, "cddl", "cddl", "the contents of this file are subject to the terms of the common development and distribution licen[sc]e"),
    (90, "ofl", "font", "this font software is licensed under the sil open font licen[sc]e"),
    (97, "unlicense", "unencumbered", "this is free and unencumbered software released into the public domain"),
    (97, "wtfpl", "fuck", "do what the fuck you want to"),
    (85, "public-domain", "domain", "(?:released|placed|dedicated|put) (?:in|into|to) the public domain"),
    (80, "public-domain", "domain", "(?:is|are|work in|belongs to) the public domain"),
    (80, "public-domain", "domain", "public domain dedication"),
    (80, "public-domain", "waives", "waives (?:all|any) (?:of )?(?:his|her|its|their) rights"),
    (92, "cc0", "publicdomain", "creativecommons org publicdomain zero 1 0"),
    (85, "cc0", "domain", "to the extent possible under law (?:W ){1,12}(?:waived|dedicated) (?:W ){1,20}public domain"),
    (90, "cc-by", "creativecommons", "creativecommons org licen[sc]es by [0-9] [0-9]"),
    (91, "cc-by-sa", "creativecommons", "creativecommons org licen[sc]es by sa [0-9] [0-9]"),
    (91, "cc-by-nc", "creativecommons", "creativecommons org licen[sc]es by nc [0-9] [0-9]"),
    (91, "cc-by-nd", "creativecommons", "creativecommons org licen[sc]es by nd [0-9] [0-9]"),
    (92, "cc-by-nc-sa", "creativecommons", "creativecommons org licen[sc]es by nc sa [0-9] [0-9]"),
    (92, "cc-by-nc-nd", "creativecommons", "creativecommons org licen[sc]es by nc nd [0-9] [0-9]"),
    (84, "cc-by-sa", "attribution", "creative commons attribution share ?alike"),
    (84, "cc-by-nc", "attribution", "creative commons attribution non ?commercial"),
    (84, "cc-by-nd", "attribution", "creative commons attribution no ?deriv(?:ative)?s"),
    (90, "sspl", "functionality", "make the functionality of the program or a modified version available to third parties as a service"),
    (90, "elastic", "hosted", "you may not provide the software to third parties as a hosted or managed service"),
    (90, "busl", "licensor", "the licensor hereby grants you the right to copy modify create derivative works redistribute and make non production use"),
    (88, "proprietary", "unauthorized", "unauthorized (?:copying|use|reproduction|distribution) of this (?:W ){1,10}is (?:strictly )?prohibited"),
    (82, "proprietary", "confidential", "(?:confidential and proprietary|proprietary and confidential)"),
    (82, "proprietary", "secret", "trade secrets? (?:of|and)"),
    (82, "reserved", "reproduced", "no part of this (?:publication|book|document|work|site|text) may be reproduced"),
    (78, "reserved", "reproduced", "may not be reproduced (?:W ){0,12}without (?:the )?(?:prior )?(?:express )?(?:written )?(?:permission|consent)"),
    (78, "reserved", "permission", "without (?:the )?(?:prior )?(?:express )?written (?:permission|consent) of the (?:publisher|author|owner|copyright holder)"),
    (76, "non-commercial", "commercial", "for (?:personal|private|internal|educational|academic)(?: and| or)? non ?commercial use only"),
    (74, "non-commercial", "commercial", "non ?commercial (?:use|purposes) only"),
    (66, "reserved", "vorbehalten", "alle rechte vorbehalten"),
    (66, "reserved", "réservés", "tous droits réservés"),
    (66, "reserved", "reservados", "todos los derechos reservados"),
    (66, "reserved", "reservados", "todos os direitos reservados"),
    (66, "reserved", "riservati", "tutti i diritti riservati"),
    (66, "reserved", "voorbehouden", "alle rechten voorbehouden"),
    (50, "copyright", "©", "© (?:copyright )?[0-9]{4}"),
]

BASE_PRIORITY = 30


@dataclass(frozen=True)
class Rule:
    """Words to find, as a pattern over normalised text; smaller order comes first among equal priorities."""

    order: int
    priority: int
    label: str
    keyword: str
    pattern: str
    base: bool


def over_words(words: str) -> str:
    """A pattern over words to one over ' word ' units: between two words there are two spaces, at the ends one."""
    return " " + words.replace(" ", "  ") + " "


def rules() -> list[Rule]:
    """All rules in order: base phrases, rules that stand alone, bodies and notices, then every form of every name."""
    raw = [(BASE_PRIORITY, label, words.split(" ")[-1], words, True) for words, label in BASE.items()]
    raw += [(p, label, key, words.replace("W ", "[^ ]+ "), False) for p, label, key, words in [*ALONE, *BODIES]]
    raw += [(p + len(name.split()) / 100, label, name.split(" ")[0], form.format(name), False) for p, form in FORMS for name, label in NAMES.items()]
    return [Rule(k, round(100 * p), label, key, over_words(words), base) for k, (p, label, key, words, base) in enumerate(raw)]


RULES = rules()


def gate(lowered: Column) -> Column:
    """True for every text that a rule could match: it holds the rule's keyword. `licen` stands for every form of a name,
    and common keywords count only beside another word of their rules."""
    cc = lowered.contains("cc") & lowered.rlike(rf"(?:^|{SEPARATOR[:-1]})cc{SEPARATOR}by(?:{SEPARATOR[:-1]}|$)")
    beside = {"later": "version", "neither": "endorse", "liable": "damages", "hosted": "software", "functionality": "third", "secret": "trade", "exception": "link", "attribution": "creative", "font": "licen", "apache": "licen", "granted": "permission"}
    found = cc | lowered.contains("licen")
    for key in sorted({k for _, _, k, _ in [*ALONE, *BODIES]} | {words.split(" ")[-1] for words in BASE.values()} - {"by", "license"}):
        if key not in ("cc", "licen"):
            found = found | (lowered.contains(key) & lowered.contains(beside[key]) if key in beside else lowered.contains(key))
    return found


def rule_array() -> Column:
    fields = lambda r: F.struct(F.lit(r.order).alias("order"), F.lit(r.priority).alias("priority"), F.lit(r.label).alias("label"), F.lit(r.keyword).alias("keyword"), F.lit(r.pattern).alias("pattern"), F.lit(r.base).alias("base"))
    return F.array(*[fields(r) for r in RULES])


SPAN = "struct<start:int,stop:int,priority:int,order:int,label:string,base:boolean>"


def spaces(text: Column) -> Column:
    return F.length(text) - F.length(F.replace(text, F.lit(" "), F.lit("")))


def spans_of(norm: Column, rule: Column) -> Column:
    """The word intervals that a rule matches: gaps and matches alternate, and each word has two spaces."""
    found = F.regexp_extract_all(norm, rule["pattern"], F.lit(0))
    gaps = F.split(norm, rule["pattern"], -1)
    start = F.struct(F.lit(0).alias("at"), F.array().cast(f"array<{SPAN}>").alias("out"))

    def step(held: Column, pair: Column) -> Column:
        begin = held["at"] + spaces(pair["gap"])
        end = begin + spaces(pair["hit"])
        span = F.struct((begin / 2).cast("int").alias("start"), (end / 2).cast("int").alias("stop"), rule["priority"].alias("priority"), rule["order"].alias("order"), rule["label"].alias("label"), rule["base"].alias("base"))
        return F.struct(end.alias("at"), F.concat(held["out"], F.array(span)).alias("out"))

    pairs = F.zip_with(F.slice(gaps, F.lit(1), F.size(found)), found, lambda g, h: F.struct(g.alias("gap"), h.alias("hit")))
    return F.aggregate(pairs, start, step, lambda held: held["out"])


def survives(span: Column, others: Column) -> Column:
    """Not inside another interval of no lower priority; of equal intervals and priorities the first rule's stays."""
    same = lambda o: (o["start"] == span["start"]) & (o["stop"] == span["stop"])
    above = lambda o: (o["priority"] > span["priority"]) | (o["priority"] == span["priority"]) & (~same(o) | (o["order"] < span["order"]))
    return ~F.exists(others, lambda o: (o["start"] <= span["start"]) & (o["stop"] >= span["stop"]) & above(o))


def scanned(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, spans.

    Null texts count as empty: no words, empty label strings, null words, score 0. The score is the highest priority
    among kept intervals, over 100. Rows are independent: repeated ids and rows give a row each, an empty table none, and
    extra columns are ignored.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    rows = rows.withColumn("lowered", F.lower("text")).select("doc_id", F.regexp_count("text", F.lit(WORD)).cast("long").alias("n_words"), F.when(gate(F.col("lowered")), F.translate("text", UPPER, LOWER)).alias("text"))
    norm = F.concat(F.lit(" "), F.trim(F.regexp_replace("text", SEPARATOR, "  ")), F.lit(" "))
    rows = rows.select("doc_id", "n_words", F.when(F.col("text").isNotNull(), norm).alias("norm"))
    spans = F.flatten(F.transform(F.filter(rule_array(), lambda r: F.contains(F.col("norm"), r["keyword"])), lambda r: spans_of(F.col("norm"), r)))
    none = F.array().cast(f"array<{SPAN}>")
    rows = rows.select("doc_id", "n_words", F.when(F.col("norm").isNotNull(), spans).otherwise(none).alias("found"))
    base = F.filter("found", lambda s: s["base"])
    rows = rows.select("doc_id", "n_words", base.alias("base"), F.filter("found", lambda s: survives(s, F.col("found"))).alias("spans"))
    named = lambda c: F.array_sort(F.array_distinct(c))
    base_names, own_names = F.transform("base", lambda s: s["label"]), F.transform("spans", lambda s: s["label"])
    starts = F.transform("base", lambda s: s["start"].cast("long"))
    return rows.select(
        "doc_id",
        "n_words",
        F.size("base").cast("long").alias("n_base"),
        F.array_min(starts).alias("first_word"),
        F.array_max(starts).alias("last_word"),
        F.array_join(named(base_names), ",").alias("base_labels"),
        F.array_join(named(F.concat(base_names, own_names)), ",").alias("labels"),
        F.coalesce(F.round(F.array_max(F.transform("spans", lambda s: s["priority"])) / 10000.0, 4), F.lit(0.0)).alias("score"),
        "spans",
    )


def scan_sql(table: str = "documents") -> str:
    """The same scan as DuckDB SQL."""
    quoted = lambda x: "'" + str(x).replace("'", "''") + "'"
    values = ", ".join(f"({r.order}, {r.priority}, {quoted(r.label)}, {quoted(r.keyword)}, {quoted(r.pattern)}, {r.base})" for r in RULES)
    gap = "length({0}) - length(replace({0}, ' ', ''))"
    return f"""
    WITH rules(ord, priority, label, keyword, pattern, base) AS (VALUES {values}),
    docs AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t FROM {table}),
    norms AS (SELECT rid, ' ' || trim(regexp_replace(translate(t, '{UPPER}', '{LOWER}'), '{SEPARATOR}', '  ', 'g')) || ' ' AS norm FROM docs),
    found AS (SELECT rid, r.*, norm, regexp_extract_all(norm, pattern) AS hits, regexp_split_to_array(norm, pattern) AS gaps
              FROM norms JOIN rules r ON contains(norm, r.keyword) WHERE regexp_matches(norm, pattern)),
    each AS (SELECT rid, ord, priority, label, base, unnest(range(1, len(hits) + 1)) AS k, hits, gaps FROM found),
    sized AS (SELECT rid, ord, priority, label, base, k, {gap.format("gaps[k]")} AS g, {gap.format("hits[k]")} AS h FROM each),
    ends AS (SELECT *, sum(g + h) OVER (PARTITION BY rid, ord ORDER BY k) AS stop FROM sized),
    spans AS (SELECT rid, ord, priority, label, base, CAST((stop - h) / 2 AS BIGINT) AS a, CAST(stop / 2 AS BIGINT) AS b FROM ends),
    kept AS (SELECT * FROM spans s WHERE NOT EXISTS (SELECT 1 FROM spans o WHERE o.rid = s.rid AND o.a <= s.a AND o.b >= s.b
             AND (o.priority > s.priority OR o.priority = s.priority AND (o.a <> s.a OR o.b <> s.b OR o.ord < s.ord)))),
    based AS (SELECT rid, count(*) AS n, min(a) AS first_word, max(a) AS last_word, string_agg(DISTINCT label, ',' ORDER BY label) AS labels FROM spans WHERE base GROUP BY rid),
    named AS (SELECT rid, string_agg(DISTINCT label, ',' ORDER BY label) AS labels
              FROM (SELECT rid, label FROM spans WHERE base UNION ALL SELECT rid, label FROM kept) GROUP BY rid),
    scored AS (SELECT rid, max(priority) AS top FROM kept GROUP BY rid)
    SELECT d.doc_id, CAST(len(regexp_extract_all(d.t, '{WORD}')) AS BIGINT) AS n_words, CAST(coalesce(b.n, 0) AS BIGINT) AS n_base, b.first_word, b.last_word,
           coalesce(b.labels, '') AS base_labels, coalesce(n.labels, '') AS labels, coalesce(round(s.top / 10000.0, 4), 0.0) AS score
    FROM docs d LEFT JOIN based b USING (rid) LEFT JOIN named n USING (rid) LEFT JOIN scored s USING (rid)
    """
