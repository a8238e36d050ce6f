"""Licence scan with a positional index of rare template words, in DataFrame expressions only.

Templates are data: their wordings and key phrases make literal arrays and maps, so
the plan is the same for any number of them. Document frequencies over the whole
corpus give every word of a key phrase its inverse document frequency, and the index
lists the two highest of each phrase with the places where they stand in it. A file's
words that the index knows, which are its rarest licence words, are looked up; each
occurrence says where in the file the phrases of its postings would begin, and what
both words of a phrase agree on is left. It is verified word by word against the
mandatory key phrase, and scored by how much of the template stands around it.
A phrase in a file has both of its indexed words there, so none is missed.
"""

from __future__ import annotations

import json
from dataclasses import dataclass
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: What a word is (of a text with A-Z in lower case).
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@dataclass(frozen=True)
class Template:
    """A licence's wording; ``key`` (part of it, or all) must stand word for word."""

    label: str
    text: str
    key: str = ""
    base: bool = False

    @property
    def words(self) -> list[str]:
        return self.text.split()

    @property
    def key_words(self) -> list[str]:
        return (self.key or self.text).split()

    @property
    def offset(self) -> int:
        w, k = self.words, self.key_words
        return next(i for i in range(len(w)) if w[i : i + len(k)] == k)


#: Base phrases and their labels.
BASE = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}
#: Sentences of licence texts and notices with the phrase that must be there.
SENTENCES = (
    Template("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction", "permission is hereby granted free of charge"),
    Template("mit", "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software", "this permission notice shall be included"),
    Template("apache-2", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license", "use this file except in compliance"),
    Template("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation", "terms of the gnu general public license"),
    Template("lgpl", "you can redistribute it and or modify it under the terms of the gnu lesser general public license", "gnu lesser general public license"),
    Template("agpl", "under the terms of the gnu affero general public license as published by the free software foundation", "gnu affero general public license"),
    Template("gfdl", "permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation license", "gnu free documentation license"),
    Template("bsd", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "redistribution and use in source and binary forms"),
    Template("bsd-3", "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software", "may be used to endorse or promote products"),
    Template("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "copy modify and or distribute this software"),
    Template("mpl-2", "this source code form is subject to the terms of the mozilla public license v 2 0", "mozilla public license"),
    Template("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software", "in no event will the authors be held liable"),
    Template("unlicense", "this is free and unencumbered software released into the public domain", "free and unencumbered software"),
    Template("bsl-1", "boost software license version 1 0", "boost software license"),
    Template("epl-2", "this program and the accompanying materials are made available under the terms of the eclipse public license 2 0", "eclipse public license"),
    Template("cddl-1", "subject to the terms of the common development and distribution license", "common development and distribution license"),
    Template("ofl-1.1", "this font software is licensed under the sil open font license version 1 1", "sil open font license"),
    Template("artistic-2", "the artistic license 2 0", "artistic license"),
    Template("eupl", "licensed under the european union public licence", "european union public licence"),
    Template("cc0", "creative commons cc0 1 0 universal", "creative commons cc0"),
)
#: Parts that versions and identifiers are made of.
GNU = {"gpl": "general", "lgpl": "lesser general", "agpl": "affero general"}
CC = {"by": "attribution", "by-sa": "attribution sharealike", "by-nd": "attribution noderivatives", "by-nc": "attribution noncommercial", "by-nc-sa": "attribution noncommercial sharealike", "by-nc-nd": "attribution noncommercial noderivatives"}
IDENTIFIERS = "MIT Apache-2.0 BSD-2-Clause BSD-3-Clause ISC MPL-2.0 Zlib Unlicense BSL-1.0 EPL-1.0 EPL-2.0 EUPL-1.2 CDDL-1.0 Artistic-2.0 WTFPL OFL-1.1 PostgreSQL NCSA Python-2.0 X11 MS-PL CC0-1.0 CC-BY-4.0 CC-BY-SA-4.0 0BSD AFL-3.0 LPPL-1.3c Ruby OSL-3.0 MulanPSL-2.0".split()
_plain = str.maketrans("-.", "  ")


def _made() -> list[Template]:
    """Templates by rule: versions of the families, short Creative Commons names, and identifier lines."""
    out = [Template(label, key, key, True) for key, label in BASE.items()] + list(SENTENCES)
    for (label, name), version, form in product(GNU.items(), "1 2 2.1 3".split(), ("version ", "v ", "")):
        out.append(Template(f"{label}-{version}", f"gnu {name} public license {form}{version}".translate(_plain)))
    for (code, name), version in product(CC.items(), "1.0 2.0 2.5 3.0 4.0".split()):
        out.append(Template(f"cc-{code}", f"creative commons {name} {version}".translate(_plain)))
        out.append(Template(f"cc-{code}", f"cc {code} {version}".translate(_plain)))
    for name in IDENTIFIERS:
        out.append(Template(name.lower(), f"spdx license identifier {name.lower().translate(_plain)}"))
    for label, version, tail in product(GNU, "2.0 2.1 3.0".split(), ("only", "or later")):
        out.append(Template(f"{label}-{version.removesuffix('.0')}", f"spdx license identifier {label} {version} {tail}".translate(_plain)))
    return out


TEMPLATES = tuple(_made())
#: Bits of a word number, moved up so that a phrase may seem to begin before its file.
_PLACE, _UP = 40, 1 << 20


def _literal(value, kind: str) -> Column:
    """A constant of any size as one expression, which the optimiser folds."""
    return F.from_json(F.lit(json.dumps({"v": value})), f"struct<v:{kind}>")["v"]


def document_frequencies(docs: DataFrame, templates: tuple[Template, ...] = TEMPLATES) -> dict[str, int]:
    """In how many rows of ``docs`` each key-phrase word occurs; as many numbers as the templates have words."""
    vocab = sorted({w for t in templates for w in t.key_words})
    words = F.regexp_extract_all(F.translate("text", UPPER, LOWER), F.lit(WORD), F.lit(0))
    some = docs.where(F.col("text").isNotNull()).select(F.explode(F.array_intersect(words, _literal(vocab, "array<string>"))).alias("w"))
    return dict.fromkeys(vocab, 0) | {r["w"]: r["n"] for r in some.groupBy("w").agg(F.count("*").alias("n")).collect()}


def anchors(t: Template, df: dict[str, int]) -> list[tuple[int, str]]:
    """(place in the key phrase, word) of its two words of the highest inverse document frequency."""
    return sorted(enumerate(t.key_words), key=lambda x: (df[x[1]], x[0]))[:2]


def postings(templates: tuple[Template, ...], df: dict[str, int], which: int) -> dict[str, list[int]]:
    """The index of the first (0) or second (-1) word: word to packed (template, place in the key phrase)."""
    out: dict[str, list[int]] = {}
    for k, t in enumerate(templates):
        place, word = anchors(t, df)[which]
        out.setdefault(word, []).append((k << _PLACE) - place)
    return out


def scan(docs: DataFrame, templates: tuple[Template, ...] = TEMPLATES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs`` with the places of base phrases, the labels and a score.

    A null text counts as empty. Texts without a key phrase get no labels, score 0 and
    null places. ``score`` is the largest share of a template that stands around one
    of its key phrases. Repeated rows and null ids are kept; an empty table gives none;
    other columns are ignored.
    """
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit("")).alias("text"))
    df = document_frequencies(rows, templates)
    index = [postings(templates, df, which) for which in (0, -1)]
    known = sorted(index[0].keys() | index[1].keys())
    keys, wholes, offsets, labels = ([f(t) for t in templates] for f in (lambda t: t.key_words, lambda t: t.words, lambda t: t.offset, lambda t: t.label))
    base = sum(t.base for t in templates)
    if not all(t.base for t in templates[:base]):
        raise ValueError("base templates come first")

    words = rows.select("doc_id", F.regexp_extract_all(F.translate("text", UPPER, LOWER), F.lit(WORD), F.lit(0)).alias("words"))
    listed = F.filter(F.transform("words", lambda w, i: F.struct(i.alias("i"), w.alias("w"))), lambda p: p["w"].isin(known))
    none = F.array().cast("array<struct<i:int,w:string>>")
    found = words.withColumn("rare", F.when(F.arrays_overlap("words", _literal(sorted(index[0]), "array<string>")), listed).otherwise(none))

    def begins(at: dict[str, list[int]]) -> Column:
        """Packed (template, where its key phrase would begin) by the postings of every rare word."""
        table = _literal(at, "map<string,array<bigint>>")
        of = lambda p: F.transform(F.coalesce(F.try_element_at(table, p["w"]), F.array().cast("array<bigint>")), lambda c: c + p["i"] + F.lit(_UP))
        return F.flatten(F.transform("rare", of))

    template = lambda c: F.shiftright(c, _PLACE).cast("int")
    place = lambda c: (c.bitwiseAND(F.lit((1 << _PLACE) - 1)) - F.lit(_UP)).cast("int")
    phrase, whole, offset, label = _literal(keys, "array<array<string>>"), _literal(wholes, "array<array<string>>"), _literal(offsets, "array<int>"), _literal(labels, "array<string>")
    both = found.withColumn("both", F.when(F.size("rare") > 0, F.array_intersect(begins(index[0]), begins(index[1]))).otherwise(F.array().cast("array<bigint>")))
    stands = lambda c: (place(c) >= 0) & (F.slice("words", F.greatest(place(c), F.lit(0)) + 1, F.size(F.get(phrase, template(c)))) == F.get(phrase, template(c)))
    hit = both.withColumn("hits", F.filter("both", stands))

    def share(c: Column) -> Column:
        text = F.get(whole, template(c))
        start = place(c) - F.get(offset, template(c))
        same = F.filter(F.transform(text, lambda w, j: (start + j >= 0) & (F.get("words", F.greatest(start + j, F.lit(0))) == w)), lambda x: x)
        return F.size(same) / F.size(text).cast("double")

    named = lambda hits: F.array_join(F.array_sort(F.array_distinct(F.transform(hits, lambda c: F.get(label, template(c))))), ",")
    of_base = F.filter("hits", lambda c: template(c) < base)
    starts = F.transform(of_base, lambda c: place(c).cast("long"))
    return hit.select(
        "doc_id",
        F.size("words").cast("long").alias("n_words"),
        F.size(of_base).cast("long").alias("n_base"),
        F.array_min(starts).alias("first_word"),
        F.array_max(starts).alias("last_word"),
        named(of_base).alias("base_labels"),
        named(F.col("hits")).alias("labels"),
        F.coalesce(F.array_max(F.transform("hits", share)), F.lit(0.0)).alias("score"),
    )


def oracle_sql(templates: tuple[Template, ...] = TEMPLATES) -> str:
    """The same result by plain search for every key phrase, for DuckDB."""
    lit = lambda ws: "[" + ",".join(f"'{w}'" for w in ws) + "]"
    table = ",\n".join(f"('{t.label}', {str(t.base).lower()}, {lit(t.words)}, {lit(t.key_words)}, {t.offset})" for t in templates)
    return f"""
WITH tpl(label, base, whole, phrase, lead) AS (VALUES {table}),
d AS (SELECT *, ' ' || array_to_string(w, ' ') || ' ' AS j FROM (SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM documents)),
f AS (SELECT rid, label, base, whole, lead, w, unnest(list_filter(range(len(w)), lambda i: w[i + 1 : i + len(phrase)] = phrase)) AS s FROM d JOIN tpl ON contains(j, ' ' || array_to_string(phrase, ' ') || ' ')),
g AS (SELECT rid, label, base, s, list_sum(list_transform(range(len(whole)), lambda k: CASE WHEN s + k - lead >= 0 AND w[s + k - lead + 1] = whole[k + 1] THEN 1 ELSE 0 END)) / len(whole) AS share FROM f),
h AS (SELECT rid, count(*) FILTER (base) AS n, min(s) FILTER (base) AS a, max(s) FILTER (base) AS b, string_agg(DISTINCT label, ',' ORDER BY label) FILTER (base) AS bl, string_agg(DISTINCT label, ',' ORDER BY label) AS l, max(share) AS m FROM g GROUP BY rid)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n, 0) AS BIGINT) AS n_base, CAST(a AS BIGINT) AS first_word, CAST(b AS BIGINT) AS last_word,
  coalesce(bl, '') AS base_labels, coalesce(l, '') AS labels, CAST(coalesce(m, 0) AS DOUBLE) AS score
FROM d LEFT JOIN h USING (rid)"""
