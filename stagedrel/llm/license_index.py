"""Licence scan with a positional rare-token index (DataFrame functions only).

Licence templates are short forms, notices and whole licence bodies, each with a mandatory key phrase. A licence word's
IDF is taken over the templates; the index holds, for each run of ``RUN`` words of a template, the places of its
``PER_RUN`` words of highest IDF, and two words of its key phrase, so that no place with the phrase is missed. A file's own licence words are looked up, highest IDF first; each of their places
implies a start for each template that they are posted in, and postings are intersected by relative position: a start
counts if two places or more agree on it. It holds the template if the key phrase stands there word by word; the score
is the share of the template's words found in their places. Base phrases (fixed by contract) are counted at every place.

As the index is a property of the templates, the result for a text does not depend on other rows.

Defined results: words are runs of ASCII letters and digits and of all characters beyond ASCII, A-Z lower-cased; a
null or empty text has 0 words and no label; repeated rows and repeated ids give a row each; nothing is grouped by
document, so extra columns and null ids do no harm; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections import Counter
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Base phrases and their labels.
BASE = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}
_AS_IS = "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software"
_BSD = "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met 1 redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer 2 redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution"
_BSD_END = "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed in no event shall the copyright holder or contributors be liable for any direct indirect incidental special exemplary or consequential damages"


def _gnu(program: str, name: str, version: str) -> str:
    return f"this {program} is free software you can redistribute it and or modify it under the terms of the {name} as published by the free software foundation either version {version} of the license or at your option any later version this {program} is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose see the {name} for more details you should have received a copy of the {name} along with this {program}"


#: Template words, the key phrase that must be there, and the label.
TEMPLATES = (
    ("this work is licensed under the gnu general public license version 3", "general public license version 3", "gpl-3.0"),
    ("gnu general public license version 2", "general public license version 2", "gpl-2.0"),
    ("gnu lesser general public license", "lesser general public license", "lgpl"),
    ("gnu affero general public license", "affero general public license", "agpl"),
    ("licensed under the apache license version 2 0", "apache license version 2 0", "apache-2.0"),
    ("released under the mit license", "mit license", "mit"),
    ("mozilla public license version 2 0", "mozilla public license", "mpl"),
    ("eclipse public license", "eclipse public license", "epl"),
    ("licensed under cc by nc 4 0", "cc by nc", "cc-by-nc"),
    ("licensed under cc by sa 4 0", "cc by sa", "cc-by-sa"),
    ("licensed under cc by nd 4 0", "cc by nd", "cc-by-nd"),
    ("creative commons attribution", "creative commons attribution", "cc-by"),
    ("all rights reserved", "all rights reserved", "all-rights-reserved"),
    (_gnu("program", "gnu general public license", "3"), "general public license as published by the free software foundation either version 3", "gpl-3.0"),
    (_gnu("program", "gnu general public license", "2"), "general public license as published by the free software foundation either version 2", "gpl-2.0"),
    (_gnu("library", "gnu lesser general public license", "2 1"), "lesser general public license as published by the free software foundation", "lgpl"),
    (_gnu("program", "gnu affero general public license", "3"), "affero general public license as published by the free software foundation", "agpl"),
    ("licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0 unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied see the license for the specific language governing permissions and limitations under the license", "you may not use this file except in compliance with the license", "apache-2.0"),
    ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software " + _AS_IS, "permission is hereby granted free of charge to any person obtaining a copy", "mit"),
    (_BSD + " " + _BSD_END, "redistribution and use in source and binary forms", "bsd"),
    (_BSD + " 3 neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission " + _BSD_END, "neither the name of the copyright holder nor the names of its contributors", "bsd-3-clause"),
    ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness", "permission to use copy modify and or distribute this software for any purpose with or without fee", "isc"),
    ("this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions 1 the origin of this software must not be misrepresented you must not claim that you wrote the original software", "permission is granted to anyone to use this software for any purpose including commercial applications", "zlib"),
    ("this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0", "subject to the terms of the mozilla public license", "mpl"),
    ("this is free and unencumbered software released into the public domain anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary for any purpose commercial or non commercial and by any means", "unencumbered software released into the public domain", "unlicense"),
    ("boost software license version 1 0 permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license", "boost software license", "bsl-1.0"),
    ("everyone is permitted to copy and distribute verbatim or modified copies of this license document and changing it is allowed as long as the name is changed", "changing it is allowed as long as the name is changed", "wtfpl"),
)
#: Words of a template that one part of the index covers, and those of them that are posted.
RUN, PER_RUN = 12, 3
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words(text: Column) -> Column:
    return F.filter(F.split(F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER), SEPARATORS), lambda w: w != "")


def places(tokens: Column, phrase: list[str]) -> Column:
    """Starts of a phrase, from 0."""
    first = F.filter(F.transform(tokens, lambda w, i: F.when(w == phrase[0], i)), lambda i: i.isNotNull())
    rest = [lambda i, k=k, w=w: F.get(tokens, i + k) == w for k, w in enumerate(phrase) if k]
    return F.filter(first, lambda i: reduce(lambda a, b: a & b, [f(i) for f in rest], F.lit(True)))


def licence_index(templates=TEMPLATES) -> tuple[list[tuple[list[str], list[str], int, str, set[int]]], list[str]]:
    """(for each template its words, its key phrase and where that stands, its label and the places that are posted; the posted words, highest IDF first)."""
    split = [(t.split(), k.split(), label) for t, k, label in templates]
    df = Counter(x for t, _, _ in split for x in set(t))
    rank = {x: (-math.log(len(split) / n), -len(x), x) for x, n in df.items()}  # ties: the longer, then by name
    out, posted = [], set()
    for t, k, label in split:
        places_of = set()
        for at in range(0, len(t), RUN):
            run = t[at : at + RUN] if len(t) - at >= RUN // 2 or not at else t[-RUN:]
            best = set(sorted(set(run), key=rank.__getitem__)[:PER_RUN])
            places_of |= {i for i in range(at, min(at + RUN, len(t))) if t[i] in best}
        first = next(i for i in range(len(t)) if t[i : i + len(k)] == k)
        best = set(sorted(set(k), key=rank.__getitem__)[:2])
        places_of |= {first + i for i, x in enumerate(k) if x in best}
        posted |= {t[i] for i in places_of}
        out.append((t, k, first, label, places_of))
    return out, sorted(posted, key=rank.__getitem__)


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_words, n_base, first_word, last_word, base_labels, labels, score (share of the best template found)."""
    index, posted = licence_index()
    strings = lambda xs: F.array(*[F.lit(x) for x in xs])
    postings: dict[str, list[Column]] = {x: [] for x in posted}
    for t, (seq, *_, at) in enumerate(index):
        for i in sorted(at):
            postings[seq[i]].append(F.struct(F.lit(t).alias("t"), F.lit(i).alias("off")))
    table = F.map_from_arrays(strings(posted), F.array(*[F.array(*postings[x]) for x in posted]))
    sequences, keys = F.array(*[strings(seq) for seq, *_ in index]), F.array(*[strings(k) for _, k, *_ in index])
    key_at, labels_of = F.array(*[F.lit(at) for _, _, at, _, _ in index]), strings([label for *_, label, _ in index])

    lowered = F.split(F.lower(F.coalesce(F.col(text_col), F.lit(""))), SEPARATORS)
    base = docs.select(F.col(id_col), F.col(text_col).alias("__text"), lowered.alias("__rough"))
    # lower() can only make more words equal to ASCII ones than lower-casing A-Z does, so no text is missed here
    base = base.select(id_col, "__text", "__rough", F.array_intersect(strings(posted), "__rough").alias("__own"))
    n_words = F.size("__rough") - (F.get("__rough", F.lit(0)) == "").cast("int") - ((F.size("__rough") > 1) & (F.element_at("__rough", -1) == "")).cast("int")
    worth = (F.size("__own") > 1) | F.arrays_overlap("__rough", strings(sorted({p.split()[-2] for p in BASE})))
    base = base.select(id_col, n_words.cast("long").alias("__rough_n"), "__own", F.when(worth, words(F.col("__text"))).alias("__w"))

    w = F.col("__w")
    # every place of the file's licence words votes; a place that two votes agree on is looked at
    placed = F.array_compact(F.transform(w, lambda x, i: F.when(F.array_contains("__own", x), F.struct(x.alias("a"), i.alias("i")))))
    votes = F.flatten(F.transform(placed, lambda s: F.transform(F.try_element_at(table, s["a"]), lambda p: F.struct(p["t"].alias("t"), (s["i"] - p["off"]).alias("s")))))
    out = base.select(id_col, "__rough_n", "__w", F.when(F.size("__own") > 1, F.sort_array(votes)).alias("__votes"))
    agreed = F.array_distinct(F.filter("__votes", lambda v, k: (k > 0) & (v == F.get("__votes", k - 1))))
    first = lambda v: v["s"] + F.get(key_at, v["t"])
    keyed = F.filter(agreed, lambda v: F.when(first(v) >= 0, F.slice(w, first(v) + 1, F.size(F.get(keys, v["t"]))) == F.get(keys, v["t"])).otherwise(False))

    def share(v: Column) -> Column:
        seq = F.get(sequences, v["t"])
        found = F.aggregate(F.transform(seq, lambda x, k: F.coalesce((F.get(w, v["s"] + k) == x).cast("int"), F.lit(0))), F.lit(0), lambda a, b: a + b)
        return F.struct(v["t"].alias("t"), (found / F.size(seq)).alias("share"))

    found = {p: places(w, p.split()) for p in BASE}
    starts = F.concat(*found.values())
    base_array = F.array_compact(F.array(*[F.when(F.size(found[p]) > 0, F.lit(v)) for p, v in BASE.items()]))
    out = out.select(
        id_col, "__rough_n", "__w", F.when(w.isNotNull(), starts).alias("__starts"), F.when(w.isNotNull(), base_array).alias("__base"),
        F.coalesce(F.transform(keyed, share), F.array().cast("array<struct<t:int,share:double>>")).alias("__hits"),
    )
    extra = F.transform("__hits", lambda h: F.get(labels_of, h["t"]))
    text = lambda a: F.array_join(F.array_sort(F.array_distinct(a)), ",")
    score = F.greatest(F.coalesce(F.array_max(F.transform("__hits", lambda h: h["share"])), F.lit(0.0)), F.when(F.size("__base") > 0, F.lit(0.5)).otherwise(0.0))
    return out.select(
        id_col,
        F.when(w.isNotNull(), F.size("__w")).otherwise(F.col("__rough_n")).cast("long").alias("n_words"),
        F.when(w.isNotNull(), F.size("__starts")).otherwise(0).cast("long").alias("n_base"),
        F.array_min("__starts").cast("long").alias("first_word"),
        F.array_max("__starts").cast("long").alias("last_word"),
        F.coalesce(text(F.col("__base")), F.lit("")).alias("base_labels"),
        F.coalesce(text(F.concat("__base", extra)), F.lit("")).alias("labels"),
        F.when(w.isNotNull(), F.round(score, 6)).otherwise(0.0).alias("score"),
    )
