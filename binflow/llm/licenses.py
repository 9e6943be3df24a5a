"""Licence recognition by sentence rules (operator 10), DataFrame functions only."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable, Mapping, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Normalised sentences of well-known licence texts and notices, and their identifiers.
SENTENCES = {
    "licensed under the apache license version 2 0": "apache-notice-2",
    "licensed under the apache license version 2 0 the license": "apache-notice-2",
    "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license": "apache-notice-2",
    "you may not use this file except in compliance with the license": "apache-compliance",
    "you may obtain a copy of the license at": "apache-copy-at",
    "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied": "apache-no-warranty",
    "see the license for the specific language governing permissions and limitations under the license": "apache-see-license",
    "mit license": "mit-title",
    "the mit license": "mit-title",
    "the mit license mit": "mit-title",
    "released under the mit license": "mit-notice",
    "licensed under the mit license": "mit-notice",
    "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions": "mit-grant",
    "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software": "mit-condition",
    "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement": "mit-no-warranty",
    "in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software": "mit-no-liability",
    "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met": "bsd-grant",
    "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer": "bsd-source",
    "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution": "bsd-binary",
    "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission": "bsd-no-endorsement",
    "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed": "bsd-no-warranty",
    "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies": "isc-grant",
    "permission to use copy modify and distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies": "isc-grant",
    "the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness": "isc-no-warranty",
    "permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions": "zlib-grant",
    "boost software license version 1 0": "boost-title",
    "distributed under the boost software license version 1 0": "boost-title",
    "this work is licensed under the gnu general public license version 3": "gpl-notice-3",
    "this work is licensed under the gnu general public license version 2": "gpl-notice-2",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version": "gpl-terms-3-later",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version": "gpl-terms-2-later",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation version 3": "gpl-notice-3",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation version 2": "gpl-notice-2",
    "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose": "gpl-no-warranty",
    "see the gnu general public license for more details": "gpl-see-details",
    "you should have received a copy of the gnu general public license along with this program": "gpl-received",
    "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 2 1 of the license or at your option any later version": "lgpl-terms-2.1-later",
    "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 3 of the license or at your option any later version": "lgpl-terms-3-later",
    "this library is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose": "lgpl-no-warranty",
    "see the gnu lesser general public license for more details": "lgpl-see-details",
    "this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license or at your option any later version": "agpl-terms-3-later",
    "see the gnu affero general public license for more details": "agpl-see-details",
    "this source code form is subject to the terms of the mozilla public license v 2 0": "mpl-notice-2",
    "if a copy of the mpl was not distributed with this file you can obtain one at https mozilla org mpl 2 0": "mpl-copy-at",
    "if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0": "mpl-copy-at",
    "this program and the accompanying materials are made available under the terms of the eclipse public license 2 0": "epl-notice-2",
    "do what the fuck you want to public license": "wtfpl-title",
    "this is free and unencumbered software released into the public domain": "unlicense-title",
    "this work is dedicated to the public domain": "public-domain",
    "licensed under cc0 1 0": "cc0",
    "licensed under cc by 4 0": "cc-by-4",
    "licensed under cc by sa 4 0": "cc-by-sa-4",
    "licensed under cc by nc 4 0": "cc-by-nc-4",
    "this work is licensed under a creative commons attribution 4 0 international license": "cc-by-4",
    "this work is licensed under a creative commons attribution sharealike 4 0 international license": "cc-by-sa-4",
    "this work is licensed under a creative commons attribution noncommercial 4 0 international license": "cc-by-nc-4",
    "all rights reserved": "all-rights-reserved",
}
#: A copyright line has free parts; its normalised form starts like this.
COPYRIGHT = r"^copyright( c)?( [0-9]{4})+( .*)?$"
# Ordered rules: (licence, identifiers that must follow each other; * may be absent). Earlier rules win.
RULES = [
    ("GPL-3.0-or-later", ["gpl-terms-3-later", "gpl-no-warranty*", "gpl-see-details*", "gpl-received*"]),
    ("GPL-2.0-or-later", ["gpl-terms-2-later", "gpl-no-warranty*", "gpl-see-details*", "gpl-received*"]),
    ("GPL-3.0-only", ["gpl-notice-3", "gpl-no-warranty*", "gpl-see-details*", "gpl-received*"]),
    ("GPL-2.0-only", ["gpl-notice-2", "gpl-no-warranty*", "gpl-see-details*", "gpl-received*"]),
    ("LGPL-3.0-or-later", ["lgpl-terms-3-later", "lgpl-no-warranty*", "lgpl-see-details*"]),
    ("LGPL-2.1-or-later", ["lgpl-terms-2.1-later", "lgpl-no-warranty*", "lgpl-see-details*"]),
    ("AGPL-3.0-or-later", ["agpl-terms-3-later", "gpl-no-warranty*", "agpl-see-details*"]),
    ("MPL-2.0", ["mpl-notice-2", "mpl-copy-at*"]),
    ("EPL-2.0", ["epl-notice-2"]),
    ("MIT", ["mit-title*", "mit-grant", "mit-condition*", "mit-no-warranty*", "mit-no-liability*"]),
    ("MIT", ["mit-notice"]),
    ("MIT", ["mit-title"]),
    ("BSD-3-Clause", ["bsd-grant", "bsd-source", "bsd-binary", "bsd-no-endorsement", "bsd-no-warranty*"]),
    ("BSD-2-Clause", ["bsd-grant", "bsd-source", "bsd-binary", "bsd-no-warranty*"]),
    ("ISC", ["isc-grant", "isc-no-warranty*"]),
    ("Zlib", ["zlib-grant"]),
    ("BSL-1.0", ["boost-title"]),
    ("Apache-2.0", ["apache-notice-2", "apache-compliance*", "apache-copy-at*", "apache-no-warranty*", "apache-see-license*"]),
    ("CC0-1.0", ["cc0"]),
    ("CC-BY-NC-4.0", ["cc-by-nc-4"]),
    ("CC-BY-SA-4.0", ["cc-by-sa-4"]),
    ("CC-BY-4.0", ["cc-by-4"]),
    ("WTFPL", ["wtfpl-title"]),
    ("Unlicense", ["unlicense-title"]),
    ("Public-Domain", ["public-domain"]),
    ("All-Rights-Reserved", ["all-rights-reserved"]),
]
#: between sentences in a cut text
_END = "\u0001"


def trigger_words(known: Iterable[str]) -> list[str]:
    """A small set of words of which every known sentence holds one (the longest words first that few others share)."""
    left, out = [set(s.split()) for s in known], []
    while left:
        counts = Counter(w for s in left for w in s)
        best = max(counts, key=lambda w: (counts[w] * len(w) ** 2, w))
        out.append(best)
        left = [s for s in left if best not in s]
    return out


def sentences(text: Column) -> Column:
    """Sentences of a text, wrapped lines kept together.

    A sentence ends at . ! or ? before white space, at a colon that ends its line, and where a
    line without letters and digits follows. Marks that open comment lines go when the
    sentence is normalised.
    """
    parts = F.regexp_replace(text, r"\n[^a-zA-Z0-9]*\n", _END)
    return F.split(F.regexp_replace(parts, r"[.!?][ \t\r\n]+|:[ \t\r]*\n", _END), _END)


def normalise(sentence: Column) -> Column:
    """Lower case; everything but a-z and 0-9 is one blank."""
    return F.trim(F.regexp_replace(F.lower(sentence), "[^a-z0-9]+", " "))


def rule_pattern(parts: list[str]) -> str:
    """Pattern of a rule over identifiers that are each written ";identifier;"."""
    return "".join(f"(?:;{p[:-1]};)?" if p.endswith("*") else f";{p};" for p in parts).replace(".", "[.]")


def recognise(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", known: Mapping[str, str] = SENTENCES, rules: Sequence[tuple[str, list[str]]] = RULES) -> DataFrame:
    """(id, sentence_ids, licences, n_unmatched) of every row.

    ``sentence_ids``: identifiers of the known sentences in order, joined by ";" (also
    copyright lines). A sentence that is wrapped over lines counts as one; one that is not
    known as a whole is looked up line by line, for lines without a full stop may stand below
    each other. ``licences``: names, in rule order, each once, joined by ";", of the rules
    found in that sequence; a rule consumes what it matches, and of two rules that fit the
    same sentences the earlier wins. ``n_unmatched``: known sentences that no rule took,
    copyright lines aside. ``known`` and ``rules`` are literals of the plan, so they are meant
    for tables of this size. A narrow plan: one scan, no shuffle, one row in memory at a time.
    Null, empty and blank texts have empty strings and zero. Rows keep their number, repeated
    and null ids included; an empty table gives no rows; other columns are not read.
    """
    look_up = F.create_map(*(F.lit(x) for pair in known.items() for x in pair))
    trigger = "|".join(sorted({"copyright", *trigger_words(known)}))
    lower = F.lower(text_col)

    def of_line(line: Column) -> Column:
        plain = normalise(line)
        return F.coalesce(look_up[plain], F.when(plain.rlike(COPYRIGHT), F.lit("copyright")))

    def of_sentence(sentence: Column) -> Column:
        whole = look_up[normalise(sentence)]
        return F.when(whole.isNotNull(), F.array(whole)).otherwise(F.transform(F.split(sentence, "\n"), of_line))

    hits = F.filter(sentences(F.col("low")), lambda s: s.rlike(trigger))
    found = F.filter(F.flatten(F.transform(hits, of_sentence)), lambda i: i.isNotNull())
    rows = docs.select(F.col(id_col).alias("id"), F.when(lower.rlike(trigger), lower).alias("low"))
    rows = rows.select("id", F.coalesce(F.array_join(found, ";"), F.lit("")).alias("sentence_ids"))
    ruled = F.filter(F.split("sentence_ids", ";"), lambda i: ~i.isin("", "copyright"))
    rows = rows.withColumn("rest", F.array_join(F.transform(ruled, lambda i: F.concat(F.lit(";"), i, F.lit(";"))), ""))
    flags = []
    for k, (name, parts) in enumerate(rules):
        pattern = rule_pattern(parts)
        rows = rows.withColumn(f"r{k}", (F.col("rest") != "") & F.col("rest").rlike(pattern))
        rows = rows.withColumn("rest", F.when(F.col(f"r{k}"), F.regexp_replace("rest", pattern, "|")).otherwise(F.col("rest")))
        flags.append(F.when(F.col(f"r{k}"), F.lit(name)))
    names = F.array_join(F.array_distinct(F.filter(F.array(*flags), lambda x: x.isNotNull())), ";")
    left = F.size(F.filter(F.split("rest", "[;|]+"), lambda x: x != ""))
    return rows.select(F.col("id").alias(id_col), "sentence_ids", names.alias("licences"), left.cast("int").alias("n_unmatched"))
