"""Licence scan by a positional index of rare licence words. DataFrame functions only."""

from __future__ import annotations

import math
from collections import Counter
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, functions as F

#: A word of the text as it is; lower-casing A-Z doesn't move its ends.
WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Rare words of a template that a file is looked up by.
RARE = 3


@dataclass(frozen=True)
class Template:
    """``words`` stand at their places, ``least`` of them at least; those of every phrase of ``keys`` all do, at their places."""

    label: str
    words: tuple[str, ...]
    keys: tuple[tuple[int, tuple[str, ...]], ...]
    base: bool = False
    least: float = 1.0

    @classmethod
    def of(cls, label: str, text: str, *keys: str, base: bool = False, least: float = 1.0) -> Template:
        words, found = tuple(text.split()), []
        for must in (tuple(k.split()) for k in keys or (text,)):
            at = next((i for i in range(len(words) - len(must) + 1) if words[i : i + len(must)] == must), None)
            if at is None:
                raise ValueError(f"{' '.join(must)!r} isn't in {text!r}")
            found.append((at, must))
        return cls(label, words, tuple(found), base, least)


# Phrases and labels of the base, then names and opening or granting words of common licences.
TEMPLATES = (
    Template.of("mit", "under the mit license", base=True),
    Template.of("apache-2", "apache license version 2", base=True),
    Template.of("cc-by-nc", "cc by nc", base=True),
    Template.of("gpl-3", "gnu general public license version 3"),
    Template.of("gpl-2", "gnu general public license version 2"),
    Template.of("lgpl", "gnu lesser general public license"),
    Template.of("agpl", "gnu affero general public license"),
    Template.of("mpl-2", "mozilla public license version 2"),
    Template.of("epl", "eclipse public license"),
    Template.of("cc-by-sa", "cc by sa"),
    Template.of("cc-by", "creative commons attribution"),
    Template.of(
        "mit",
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files",
        "hereby granted free of charge", least=0.8,
    ),
    Template.of(
        "mit",
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction "
        "including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so "
        "subject to the following conditions the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
        "hereby granted free of charge", "sublicense and or sell copies", least=0.7,
    ),
    Template.of(
        "bsd",
        "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
        "source and binary forms", least=0.8,
    ),
    Template.of(
        "bsd",
        "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
        "redistributions of source code must retain", least=0.8,
    ),
    Template.of(
        "bsd-3",
        "may be used to endorse or promote products derived from this software without specific prior written permission",
        "endorse or promote products", least=0.8,
    ),
    Template.of(
        "isc",
        "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
        "with or without fee", least=0.6,
    ),
    Template.of(
        "apache-2",
        "you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0",
        "you may not use this file except in compliance", least=0.7,
    ),
    Template.of(
        "gpl",
        "is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation",
        "redistribute it and or modify it", "gnu general public license", least=0.8,
    ),
    Template.of(
        "lgpl",
        "is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation",
        "redistribute it and or modify it", "gnu lesser general public license", least=0.8,
    ),
    Template.of(
        "mpl-2",
        "this source code form is subject to the terms of the mozilla public license v 2 0",
        "subject to the terms of the mozilla public license", least=0.8,
    ),
    Template.of("unlicense", "this is free and unencumbered software released into the public domain", "free and unencumbered software", least=0.8),
    Template.of(
        "zlib",
        "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software",
        "authors be held liable for any damages", least=0.8,
    ),
    Template.of(
        "bsl-1",
        "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license",
        "person or organization obtaining a copy", least=0.8,
    ),
)


def index(templates: tuple[Template, ...] = TEMPLATES) -> list[list[tuple[str, int]]]:
    """For each template its postings (word, place): the words of its key phrases with the highest inverse document frequency among the templates, RARE
    at most, each once in the template. All of them stand in every match, since key phrases are mandatory."""
    holds = Counter(w for t in templates for w in set(t.words))
    out = []
    for t in templates:
        must = {w for _, k in t.keys for w in k if t.words.count(w) == 1}
        if not must:
            raise ValueError(f"the key phrases of {t.label} need a word that the template holds once")
        idf = {w: math.log(len(templates) / holds[w]) for w in must}
        out.append([(w, t.words.index(w)) for w in sorted(must, key=lambda w: (-idf[w], -len(w), w))[:RARE]])
    return out


def _of(word: str) -> Column:
    """The file's places of a listed word."""
    return F.transform(F.filter("hits", lambda p: p.w == word), lambda p: p.i)


def _starts(postings: list[tuple[str, int]], places: dict[str, Column]) -> Column:
    """Where a template may begin: the file's places of each rare word, shifted by the word's place in the template, intersected."""

    def shifted(word: str, at: int) -> Column:
        return F.transform(places[word], lambda i: i - F.lit(at))

    return reduce(F.array_intersect, [shifted(w, at) for w, at in postings])


def _verified(t: Template, starts: Column, words: Column) -> Column:
    """The starts at which all key phrases stand, with the share of the template's words that stand at their places."""
    n = len(t.words)

    def window(start: Column, at: int, length: int) -> Column:
        """``length`` words from a place on; beyond the text's ends they are null."""
        return F.transform(F.sequence(F.lit(at), F.lit(at + length - 1)), lambda j: F.get(words, start + j))

    def place(start: Column) -> Column:
        must = F.lit(True)
        for at, key in t.keys:
            must = must & (window(start, at, len(key)) == F.array(*map(F.lit, key)))
        same = F.zip_with(window(start, 0, n), F.array(*map(F.lit, t.words)), lambda a, b: F.coalesce((a == b).cast("int"), F.lit(0)))
        cover = F.lit(1.0) if t.least == 1.0 and t.keys == ((0, t.words),) else F.aggregate(same, F.lit(0), lambda x, y: x + y) / F.lit(float(n))
        return F.struct(F.lit(t.label).alias("label"), F.lit(t.base).alias("base"), start.cast("long").alias("start"), F.when(F.coalesce(must, F.lit(False)), cover).otherwise(F.lit(0.0)).cast("double").alias("cover"))

    return F.filter(F.transform(starts, place), lambda x: x.cover >= t.least)


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", templates: tuple[Template, ...] = TEMPLATES) -> DataFrame:
    """One row per document: id, ``n_words``, ``n_base``, ``first_word``, ``last_word``, ``base_labels``, ``labels``, ``score``, ``places``.

    Words are ``[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+`` after lower-casing A-Z; null counts as empty, and whole texts are read, however long. Base
    phrases count at every place where their words stand one after another; ``first_word`` and ``last_word`` are the smallest and largest start, null
    without any. Labels are distinct, sorted and joined by commas, empty without any. ``score`` is the best share of a template's words found at
    their places. ``places`` lists every match; a template's start lies before the text's where only its later words are there. A row that
    repeats an id, or has none, is a document of its own. Other columns are ignored; an empty table gives an empty result.

    A file is looked up by the licence words of highest inverse document frequency that it holds: their places, shifted by the words' places in a
    template, are intersected, and only at what remains are the mandatory key phrases and the other words compared. A document's words are only taken apart
    when it holds, as a whole word, the rarest word of some template.
    """
    posts = index(templates)
    firsts = sorted({p[0][0] for p in posts})
    listed = sorted({w for p in posts for w, _ in p})
    edge = "[^\\x00-\\x2F\\x3A-\\x40\\x5B-\\x60\\x7B-\\x7F]"
    any_rare = f"(?i)(?<!{edge})(?:" + "|".join(firsts) + f")(?!{edge})"
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).alias(id_col), F.regexp_count(text, F.lit(WORD)).cast("long").alias("n_words"), F.when(text.rlike(any_rare), F.regexp_extract_all(F.translate(text, UPPER, LOWER), F.lit(WORD), F.lit(0))).alias("words"))
    # Places of the listed words only, then those of each word: a text's other words are passed over once.
    hits = F.filter(F.transform("words", lambda w, i: F.struct(w.alias("w"), i.alias("i"))), lambda p: p.w.isin(*listed))
    rows = rows.withColumn("hits", hits)
    rows = rows.withColumn("at", F.when(F.size("hits") > 0, F.struct(*[_of(w).alias(f"w{n}") for n, w in enumerate(listed)])))
    places = {w: F.col(f"at.w{n}") for n, w in enumerate(listed)}
    starts = F.when(F.col("at").isNotNull(), F.struct(*[_starts(p, places).alias(f"t{n}") for n, p in enumerate(posts)]))
    rows = rows.select(id_col, "n_words", "words", starts.alias("starts"))
    found = F.concat(*[F.when(F.size(F.col(f"starts.t{n}")) > 0, _verified(t, F.col(f"starts.t{n}"), F.col("words"))).otherwise(F.array().cast("array<struct<label:string,base:boolean,start:bigint,cover:double>>")) for n, t in enumerate(templates)])
    none = F.array().cast("array<struct<label:string,base:boolean,start:bigint,cover:double>>")
    rows = rows.select(id_col, "n_words", F.when(F.col("starts").isNotNull(), found).otherwise(none).alias("places"))
    base = F.filter("places", lambda x: x.base)
    first = F.transform(base, lambda x: x.start)
    join = lambda xs: F.array_join(F.array_sort(F.array_distinct(F.transform(xs, lambda x: x.label))), ",")
    return rows.select(
        id_col, "n_words", F.size(base).cast("long").alias("n_base"), F.array_min(first).alias("first_word"), F.array_max(first).alias("last_word"),
        join(base).alias("base_labels"), join(F.col("places")).alias("labels"), F.coalesce(F.array_max(F.transform("places", lambda x: x.cover)), F.lit(0.0)).alias("score"), "places",
    )
