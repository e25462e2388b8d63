"""Licence scan with a positional rare-token index, in DataFrame functions only.

Templates are the passages of licence texts (grants, conditions, disclaimers, notices) with a mandatory
key phrase in each. The index posts every word of the key phrases to its templates and its places in
them; inverse document frequencies are counted over all texts.

1. Look-up: of a text's licence words the ones of highest inverse document frequency are looked up. A key
   phrase can only stand where all its words do, so for each template these are its two rarest words.
2. Intersection: a word's place less its place in the template is where the template would begin. The
   places that the two words' postings give are intersected.
3. Verification: there the key phrase must stand verbatim; the template's score is the share of
   its words that stand where they should, and a share of ``SHARE`` or more gives its label.

Since a place of a key phrase always holds both looked-up words at their distance, none is missed. All
of it is local to a row but the frequencies, one aggregate of at most one row a licence word.

Words are cut and folded at ASCII letters only: the two other characters that folding would turn into
ASCII letters are replaced first; what folding does inside other words changes neither their number
nor a comparison with a template.

Defined results: null and empty texts have no words, no places, empty label strings and score 0;
repeated rows are scanned alike; ids play no part; extra columns are ignored; an empty table gives
an empty result (all words then tie and the longest are looked up).
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .runtime import table

SHARE = 0.6
SPLIT = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


@dataclass(frozen=True)
class Template:
    label: str
    words: tuple[str, ...]
    key: tuple[int, int]  # first word and end of the mandatory phrase
    base: bool = False

    @property
    def phrase(self) -> tuple[str, ...]:
        return self.words[self.key[0] : self.key[1]]


def template(label: str, text: str, key: str, base: bool = False) -> Template:
    words, phrase = text.split(), key.split()
    at = next(i for i in range(len(words)) if words[i : i + len(phrase)] == phrase)
    return Template(label, tuple(words), (at, at + len(phrase)), base)


# fixed values: base phrases, then the passages of customary licence texts and notices, with the phrase that must be there
TEMPLATES = [
    template("cc-by", "cc by", "cc by", True),
    template("gpl", "general public license", "general public license", True),
    template("reserved", "all rights reserved", "all rights reserved", True),
    template("apache-2.0", "licensed under the apache license version 2 0", "apache license"),
    template("apache-2.0", "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0", "you may not use this file except in compliance"),
    template("apache-2.0", "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied see the license for the specific language governing permissions and limitations under the license", "on an as is basis without warranties or conditions"),
    template("mit", "released under the mit license", "mit license"),
    template("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software", "permission is hereby granted free of charge"),
    template("mit", "to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions", "merge publish distribute sublicense"),
    template("mit", "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software", "in no event shall the authors or copyright holders be liable"),
    template("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "redistribution and use in source and binary forms"),
    template("bsd", "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer", "redistributions of source code must retain"),
    template("bsd", "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution", "redistributions in binary form must reproduce"),
    template("bsd", "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed", "provided by the copyright holders and contributors"),
    template("bsd-3", "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission", "may be used to endorse or promote products"),
    template("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies", "permission to use copy modify"),
    template("lgpl", "gnu lesser general public license", "lesser general public license"),
    template("agpl", "gnu affero general public license", "affero general public license"),
    template("gpl-3.0", "gnu general public license version 3", "general public license version 3"),
    template("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version", "you can redistribute it and or modify it under the terms"),
    template("gpl", "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose see the gnu general public license for more details", "in the hope that it will be useful"),
    template("mpl-2.0", "mozilla public license version 2 0", "mozilla public license"),
    template("mpl-2.0", "this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at", "this source code form is subject to the terms"),
    template("epl", "eclipse public license", "eclipse public license"),
    template("zlib", "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software", "in no event will the authors be held liable"),
    template("zlib", "the origin of this software must not be misrepresented you must not claim that you wrote the original software", "must not be misrepresented"),
    template("bsl-1.0", "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license", "to any person or organization obtaining a copy"),
    template("cc-by-nc", "licensed under cc by nc 4 0", "cc by nc"),
    template("cc-by-sa", "licensed under cc by sa 4 0", "cc by sa"),
    template("cc-by", "this work is licensed under a creative commons attribution 4 0 international license", "creative commons attribution 4 0"),
    template("cc0", "cc0 1 0 universal public domain dedication", "cc0 1 0 universal"),
    template("unlicense", "this is free and unencumbered software released into the public domain", "free and unencumbered software"),
    template("unlicense", "anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary for any purpose commercial or non commercial and by any means", "anyone is free to copy modify publish use"),
]
LEXICON = sorted({w for t in TEMPLATES for w in t.phrase})


def words_of(text: Column) -> Column:
    """Words of a text, case folded."""
    plain = F.replace(F.replace(F.coalesce(text, F.lit("")), F.lit("\u212a"), F.lit("\u00a4")), F.lit("\u0130"), F.lit("\u00a4"))
    return F.array_remove(F.split(F.lower(plain), SPLIT), "")


def frequencies(docs: DataFrame) -> dict[str, int]:
    """In how many texts each word of the key phrases occurs; at most one row for each."""
    present = F.array_intersect(words_of(F.col("text")), F.lit(LEXICON))
    rows = docs.select(F.explode(present).alias("word")).groupBy("word").agg(F.count("*").alias("n")).collect()
    return {r.word: r.n for r in rows}


def rarest(t: Template, df: dict[str, int]) -> list[int]:
    """Places in the key phrase of its two rarest words, the longer of equally rare ones first."""
    return sorted(range(len(t.phrase)), key=lambda i: (df.get(t.phrase[i], 0), -len(t.phrase[i]), i))[:2]


def _share(t: Template, at: Column) -> Column:
    """The share of a template's words that stand where they should if its key phrase begins at ``at``."""
    same = F.transform(F.lit(list(t.words)), lambda w, j: F.coalesce(F.get("words", at + j - t.key[0]) == w, F.lit(False)))
    return F.size(F.filter(same, lambda x: x)) / F.lit(float(len(t.words)))


def scan(docs: DataFrame, templates: list[Template] = TEMPLATES, df: dict[str, int] | None = None) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_words, places (label, first word, share) and the summary columns."""
    df = frequencies(docs) if df is None else df
    chosen = {t: rarest(t, df) for t in templates}
    first = sorted({t.phrase[own[0]] for t, own in chosen.items()})
    lookup = sorted({t.phrase[i] for t, own in chosen.items() for i in own})
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), words_of(F.col("text")).alias("words"))
    positions = F.filter(F.transform("words", lambda w, i: F.struct(w.alias("w"), i.alias("i"))), lambda x: F.array_contains(F.lit(lookup), x["w"]))
    none = F.lit(None).cast("array<struct<w:string,i:int>>")
    rows = rows.select("doc_id", "words", F.when(F.arrays_overlap("words", F.lit(first)), positions).otherwise(none).alias("hits"))

    def begins(t: Template, i: int) -> Column:
        """Where the key phrase would begin by the postings of its i-th word."""
        return F.transform(F.filter("hits", lambda h: h["w"] == t.phrase[i]), lambda h: h["i"] - i)

    def places(t: Template) -> Column:
        own = reduce(F.array_intersect, [begins(t, i) for i in chosen[t]])
        return F.filter(own, lambda s: (s >= 0) & (F.slice("words", F.greatest(s, F.lit(0)) + 1, len(t.phrase)) == F.lit(list(t.phrase))))

    def found(t: Template) -> Column:
        return F.transform(places(t), lambda s: F.struct(F.lit(t.label).alias("label"), s.alias("at"), _share(t, s).alias("share"), F.lit(t.base).alias("base")))

    every = F.when(F.col("hits").isNotNull(), F.filter(F.concat(*[found(t) for t in templates]), lambda p: p["share"] >= SHARE))
    every = F.coalesce(every, F.array().cast("array<struct<label:string,at:int,share:double,base:boolean>>"))
    rows = rows.select("doc_id", F.size("words").cast("long").alias("n_words"), every.alias("places"))
    base = F.filter("places", lambda p: p["base"])
    label = lambda c: F.array_join(F.array_sort(F.array_distinct(F.transform(c, lambda p: p["label"]))), ",")
    return rows.select(
        "doc_id", "n_words",
        F.size(base).cast("long").alias("n_base"),
        F.array_min(F.transform(base, lambda p: p["at"])).cast("long").alias("first_word"),
        F.array_max(F.transform(base, lambda p: p["at"])).cast("long").alias("last_word"),
        label(base).alias("base_labels"), label("places").alias("labels"),
        F.coalesce(F.array_max(F.transform("places", lambda p: p["share"])), F.lit(0.0)).alias("score"),
        "places",
    )


def op4_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents")).drop("places")


def _oracle() -> str:
    parts = []
    for t in TEMPLATES:
        k, n = t.key[0], len(t.phrase)
        same = " + ".join([str(n)] + [f"(CASE WHEN i + {j - k} >= 1 AND w[i + {j - k}] = '{x}' THEN 1 ELSE 0 END)" for j, x in enumerate(t.words) if not t.key[0] <= j < t.key[1]])
        quoted = ", ".join(f"'{x}'" for x in t.phrase)
        parts.append(f"SELECT r, '{t.label}' AS label, {str(t.base).lower()} AS base, i - 1 AS pos, ({same})::DOUBLE / {float(len(t.words))} AS share FROM p WHERE w[i:i + {n - 1}] = [{quoted}]")
    return f"""
WITH d AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{SPLIT}'), lambda x: x <> '') AS w FROM documents),
p AS (SELECT r, w, unnest(range(1, len(w) + 1)) AS i FROM d WHERE list_has_any(w, [{", ".join(sorted({f"'{max(t.phrase, key=len)}'" for t in TEMPLATES}))}])),
f AS (SELECT r, label, base, pos, share FROM ({" UNION ALL ".join(parts)}) WHERE share >= {SHARE}),
g AS (SELECT r, (count(*) FILTER (base))::BIGINT AS n_base, (min(pos) FILTER (base))::BIGINT AS first_word, (max(pos) FILTER (base))::BIGINT AS last_word,
  string_agg(DISTINCT label, ',' ORDER BY label) FILTER (base) AS base_labels, string_agg(DISTINCT label, ',' ORDER BY label) AS labels, max(share) AS score FROM f GROUP BY r)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(g.n_base, 0) AS n_base, g.first_word, g.last_word, coalesce(g.base_labels, '') AS base_labels, coalesce(g.labels, '') AS labels, coalesce(g.score, 0.0) AS score
FROM d LEFT JOIN g USING (r)
"""


ORACLE = _oracle()
