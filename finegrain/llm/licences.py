"""Licence scan by a positional index of rare tokens.

Of every licence text the index holds its words of highest inverse document frequency with their positions. The heaviest of them,
enough that no place with ``ENOUGH`` of the weight can do without all, are anchors: each anchor found in a file names a place, the first word that
the licence text would have there, and the other rare words are looked up at their relative positions from it. Places where
enough of the weight stands are candidates, and a candidate counts once all its mandatory key phrases stand in the file. Base phrases (a
phrase's words in a row) are found in the same pass.

Everything is column expressions over one row: no shuffle, no Python. A file's words are passed once and an anchor costs a fixed number
of lookups, so the work grows with the text.

Defined results: a null text counts as empty; a text without words has no labels, null first and last word and score 0.
Extra columns pass through under any names; the columns added here replace input columns of the same name.
"""

from __future__ import annotations

import json
import math
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from finegrain.llm.rows import column, packed, unpacked

# Base phrases and their labels.
BASE_PHRASES = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}

# Notices of public licences (label: notice words, mandatory key phrases).
NOTICES = {
    "notice:mit": ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", ["permission is hereby granted free of charge"]),
    "notice:isc": ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", ["with or without fee"]),
    "notice:apache-2.0": ("licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license", ["apache license version 2 0"]),
    "notice:bsd": ("redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", ["redistribution and use in source and binary forms"]),
    "notice:mpl-2.0": ("this source code form is subject to the terms of the mozilla public license v 2 0", ["mozilla public license"]),
    "notice:unlicense": ("this is free and unencumbered software released into the public domain", ["unencumbered software released into the public domain"]),
    "notice:cc0": ("to the extent possible under law the author has dedicated all copyright to this work under cc0 1 0 universal", ["cc0 1 0"]),
    "line:apache-2.0": ("licensed under the apache license version 2 0", ["apache license version 2 0"]),
    "line:gpl-2.0": ("this work is licensed under the gnu general public license version 2", ["general public license version 2"]),
    "line:gpl-3.0": ("this work is licensed under the gnu general public license version 3", ["general public license version 3"]),
    "line:lgpl": ("licensed under the gnu lesser general public license", ["gnu lesser general public license"]),
    "line:agpl": ("licensed under the gnu affero general public license", ["gnu affero general public license"]),
    "line:cc-by-4.0": ("licensed under cc by 4 0", ["cc by 4 0"]),
    "line:cc-by-sa-4.0": ("licensed under cc by sa 4 0", ["cc by sa 4 0"]),
    "line:cc-by-nc-4.0": ("licensed under cc by nc 4 0", ["cc by nc 4 0"]),
    "line:cc-by-nd-4.0": ("licensed under cc by nd 4 0", ["cc by nd 4 0"]),
    "line:mit": ("released under the mit license", ["mit license"]),
}

# Bodies of public licences in lower-cased words (label: body words, mandatory key phrases).
BODIES = {
    "body:mit": (
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction "
        "including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished "
        "to do so subject to the following conditions the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software the software "
        "is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement in "
        "no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection "
        "with the software or the use or other dealings in the software",
        ["to deal in the software without restriction", "the software is provided as is"],
    ),
    "body:isc": (
        "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice "
        "appear in all copies the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness "
        "in no event shall the author be liable for any special direct indirect or consequential damages or any damages whatsoever resulting from loss of use data or profits whether in an action "
        "of contract negligence or other tortious action arising out of or in connection with the use or performance of this software",
        ["with or without fee", "the author disclaims all warranties"],
    ),
    "body:bsd-2": (
        "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met 1 redistributions of source code must retain "
        "the above copyright notice this list of conditions and the following disclaimer 2 redistributions in binary form must reproduce the above copyright notice this list of conditions and the "
        "following disclaimer in the documentation and or other materials provided with the distribution this software is provided by the copyright holders and contributors as is and any express "
        "or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed in no event shall the copyright holder or "
        "contributors be liable for any direct indirect incidental special exemplary or consequential damages",
        ["redistribution and use in source and binary forms", "are disclaimed"],
    ),
    "body:bsd-3": (
        "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
        ["endorse or promote products derived from this software"],
    ),
    "body:zlib": (
        "this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software permission is "
        "granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions 1 the origin of "
        "this software must not be misrepresented you must not claim that you wrote the original software if you use this software in a product an acknowledgment in the product documentation "
        "would be appreciated but is not required 2 altered source versions must be plainly marked as such and must not be misrepresented as being the original software 3 this notice may not be "
        "removed or altered from any source distribution",
        ["must not be misrepresented"],
    ),
    "body:boost": (
        "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license the software to use "
        "reproduce display distribute execute and transmit the software and to prepare derivative works of the software and to permit third parties to whom the software is furnished to do so",
        ["reproduce display distribute execute and transmit the software"],
    ),
    "body:unlicense": (
        "this is free and unencumbered software released into the public domain anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as "
        "a compiled binary for any purpose commercial or non commercial and by any means in jurisdictions that recognize copyright laws the author or authors of this software dedicate any and all "
        "copyright interest in the software to the public domain we make this dedication for the benefit of the public at large and to the detriment of our heirs and successors",
        ["released into the public domain"],
    ),
    "body:apache-2.0": (
        "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org "
        "licenses license 2 0 unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of "
        "any kind either express or implied see the license for the specific language governing permissions and limitations under the license",
        ["apache license version 2 0", "unless required by applicable law or agreed to in writing"],
    ),
    "body:gpl-2.0": (
        "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of "
        "the license or at your option any later version this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of "
        "merchantability or fitness for a particular purpose see the gnu general public license for more details",
        ["under the terms of the gnu general public license", "either version 2 of the license"],
    ),
    "body:gpl-3.0": (
        "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of "
        "the license or at your option any later version this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of "
        "merchantability or fitness for a particular purpose see the gnu general public license for more details",
        ["under the terms of the gnu general public license", "either version 3 of the license"],
    ),
    "body:lgpl": (
        "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either "
        "version 2 1 of the license or at your option any later version this library is distributed in the hope that it will be useful but without any warranty",
        ["gnu lesser general public license"],
    ),
    "body:agpl-3.0": (
        "this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either "
        "version 3 of the license or at your option any later version",
        ["gnu affero general public license"],
    ),
    "body:mpl-2.0": (
        "this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0",
        ["mozilla public license"],
    ),
    "body:cc-by-4.0": (
        "you are free to share copy and redistribute the material in any medium or format and adapt remix transform and build upon the material for any purpose even commercially the licensor "
        "cannot revoke these freedoms as long as you follow the license terms under the following terms attribution you must give appropriate credit provide a link to the license and indicate if "
        "changes were made",
        ["you must give appropriate credit"],
    ),
    "body:wtfpl": (
        "everyone is permitted to copy and distribute verbatim or modified copies of this license document and changing it is allowed as long as the name is changed",
        ["verbatim or modified copies of this license document"],
    ),
}
TEXTS = NOTICES | BODIES

# Words too common in running text to index.
COMMON_WORDS = ("the", "of", "to", "and", "or", "in", "is", "are", "any", "for", "this", "that", "with", "by", "a", "you", "not", "has", "all")

#: A word of the text: the contract's class, upper-case letters included as they are lowered only in candidate files.
WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
#: Rare words kept of a notice and of a body, and the share of their weight that must agree in relative position.
RARE_WORDS, RARE_BODY_WORDS, ENOUGH = 8, 16, 0.6
#: One of these strings stands in every text with a base phrase or a key phrase.
TELLING = "(?i)licen[sc]e|cc[^a-z0-9]+by|cc0|permission|with or without|redistribution|unencumbered|without[^a-z]+fee|misrepresented|endorse|appropriate|transmit"


def positional_index() -> dict[str, list[tuple[str, int, float]]]:
    """Postings ``(word, position, idf)`` of every text: its rarest words over all texts, heaviest first, ties by position."""
    frequency = Counter(w for words, _ in TEXTS.values() for w in set(words.split()))
    index = {}
    for label, (words, _) in TEXTS.items():
        weighed = [(math.log((len(TEXTS) + 1) / frequency[w]), k, w) for k, w in enumerate(words.split()) if w not in COMMON_WORDS]
        kept = sorted(weighed, key=lambda x: (-x[0], x[1]))[: RARE_WORDS if label in NOTICES else RARE_BODY_WORDS]
        index[label] = [(w, k, idf) for idf, k, w in kept]
    return index


def anchors_of(postings: list[tuple[str, int, float]]) -> int:
    """How many of the heaviest postings are anchors: what is left of the weight without them is too little for a place."""
    total, left = sum(p[2] for p in postings), sum(p[2] for p in postings)
    for n, (_, _, idf) in enumerate(postings):
        if left < ENOUGH * total - 1e-9:
            return n
        left -= idf
    return len(postings)


def anchor_table() -> dict[str, list[tuple[str, int, int]]]:
    """By word: ``(label, its number among the label's postings, position)`` of the places that it anchors."""
    table: dict[str, list[tuple[str, int, int]]] = {}
    for label, postings in positional_index().items():
        for n, (word, k, _) in enumerate(postings[: anchors_of(postings)]):
            table.setdefault(word, []).append((label, n, k))
    return table


def _phrase_at(words: Column, at: Column, phrase: str) -> Column:
    """Whether the phrase's words stand in ``words`` from position ``at`` on."""
    hit = F.lit(True)
    for k, w in enumerate(phrase.split()):
        hit = hit & F.coalesce(F.get(words, at + k) == w, F.lit(False))
    return hit


def _places(phrase: str, label: str) -> Column:
    """Where the base phrase stands: an array of word position and label."""
    at = F.filter("found", lambda x: (x["w"] == phrase.split()[0]) & _phrase_at(F.col("words"), x["i"], phrase))
    return F.transform(at, lambda x: F.struct(x["i"].alias("i"), F.lit(label).alias("label")))


def _constant(value: dict, kind: str) -> Column:
    """A literal of a nested type: one expression, worked out once when the plan is optimised."""
    return F.from_json(F.lit(json.dumps(value)), kind)


def _candidates() -> Column:
    """Places of licence texts with enough of their weight: an array of label, first word's position and share, each place once."""
    peers = {}
    for label, postings in positional_index().items():
        whole = sum(p[2] for p in postings)
        peers[label] = [{"w": w, "k": k, "share": idf / whole} for w, k, idf in postings]
    spots = {word: [{"label": label, "n": n, "k": k, "peers": peers[label]} for label, n, k in places] for word, places in anchor_table().items()}
    table = _constant(spots, "map<string, array<struct<label: string, n: int, k: int, peers: array<struct<w: string, k: int, share: double>>>>>")
    words = F.col("words")

    def place(x: Column, spot: Column) -> Column:
        at = x["i"] - spot["k"]
        stands = lambda p: F.coalesce(F.when(at + p["k"] >= 0, F.get(words, at + p["k"])) == p["w"], F.lit(False))
        # an earlier anchor that stands there names the same place
        earlier = F.exists(F.slice(spot["peers"], F.lit(1), spot["n"]), stands)
        share = F.aggregate(spot["peers"], F.lit(0.0), lambda acc, p: acc + F.when(stands(p), p["share"]).otherwise(0.0))
        return F.struct(spot["label"].alias("label"), at.alias("at"), F.when(earlier, F.lit(0.0)).otherwise(F.least(F.lit(1.0), share)).alias("share"))

    anchored = F.filter(F.transform("found", lambda x: F.struct(x["i"].alias("i"), F.try_element_at(table, x["w"]).alias("spots"))), lambda x: x["spots"].isNotNull())
    named = F.flatten(F.transform(anchored, lambda x: F.transform(x["spots"], lambda spot: place(x, spot))))
    return F.filter(named, lambda s: s["share"] >= ENOUGH - 1e-9)


OWN = ("n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "notices")


def scan_licences(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with ``n_words``, ``n_base``, ``first_word``, ``last_word``, ``base_labels``, ``labels``, ``score`` and
    ``notices`` (array of label, first word of the place, share of its weight found)."""
    docs = docs.drop(*(c for c in OWN if c != text))
    needed = sorted({p.split()[0] for p in BASE_PHRASES} | set(anchor_table()))
    rows = packed(docs, body=F.coalesce(column(text), F.lit("")))
    rows = rows.withColumn("n_words", F.regexp_count("body", F.lit(WORD)).cast("long"))
    lowered = F.translate("body", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    rows = rows.withColumn("words", F.when(F.col("body").rlike(TELLING), F.regexp_extract_all(lowered, F.lit(WORD), F.lit(0)))).drop("body")
    found = F.filter(F.transform("words", lambda w, i: F.struct(w.alias("w"), i.alias("i"))), lambda x: x["w"].isin(needed))
    rows = rows.withColumn("found", F.coalesce(found, F.array().cast("array<struct<w:string,i:int>>")))
    rows = rows.withColumn("base", F.concat(*(_places(phrase, label) for phrase, label in BASE_PHRASES.items())))
    rows = rows.withColumn("candidates", _candidates())
    line = F.concat(F.lit(" "), F.array_join("words", " "), F.lit(" "))
    rows = rows.withColumn("line", F.when(F.size("candidates") > 0, line))
    phrases = _constant({label: [f" {p} " for p in keys] for label, (_, keys) in TEXTS.items()}, "map<string, array<string>>")
    labelled = F.array_distinct(F.transform("candidates", lambda s: s["label"]))
    rows = rows.withColumn("sure", F.filter(labelled, lambda x: F.forall(F.element_at(phrases, x), lambda p: F.contains(F.col("line"), p))))
    rows = rows.withColumn("notices", F.filter("candidates", lambda s: F.array_contains("sure", s["label"])))
    base_labels = F.array_distinct(F.transform("base", lambda b: b["label"]))
    best = F.array_max(F.transform("notices", lambda s: s["share"]))
    rows = (
        rows.withColumn("n_base", F.size("base").cast("long"))
        .withColumn("first_word", F.array_min(F.transform("base", lambda b: b["i"])).cast("long"))
        .withColumn("last_word", F.array_max(F.transform("base", lambda b: b["i"])).cast("long"))
        .withColumn("base_labels", F.array_join(F.array_sort(base_labels), ","))
        .withColumn("labels", F.array_join(F.array_sort(F.array_union(base_labels, "sure")), ","))
        .withColumn("score", F.coalesce(best, F.when(F.size("base") > 0, 0.5).otherwise(0.0)))
    )
    return unpacked(rows, docs.columns, *(c for c in OWN if c not in docs.columns))
