"""Licence recognition by sentences: known sentences become identifiers, identifier sequences meet ordered rules.

Only DataFrame functions are used, and only on documents that hold one of the anchor words which every known
sentence has. The sentence table and the rules are fixed and small; they are literals of the plan.

Defined results: null or empty text has no licence; a known sentence may be wrapped over lines and
hold stops; sentences that are not known break no sequence, but identifiers must follow each other
in the rule's order; rules are tried from the most specific, and what a rule has used is not matched again;
repeated rows each get a result; an empty table gives no rows. Only the named columns are read.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .state import let

# Identifiers of licence sentences, and the sentences as licence texts have them.
SENTENCES = (
    ("mit_name", "Released under the MIT License."),
    ("mit_name", "Licensed under the MIT License."),
    ("mit_name", "This project is licensed under the MIT License."),
    ("mit_grant", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"),
    ("mit_notice", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("as_is", "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT."),
    ("apache2_name", "Licensed under the Apache License, Version 2.0."),
    ("apache2_name", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License."),
    ("apache2_obtain", "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0"),
    ("apache2_limits", "See the License for the specific language governing permissions and limitations under the License."),
    ("gpl3_name", "This work is licensed under the GNU General Public License, version 3."),
    ("gpl3_name", "Licensed under the GNU General Public License, version 3."),
    ("gpl2_name", "This work is licensed under the GNU General Public License, version 2."),
    ("gpl_free", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("gpl_hope", "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE."),
    ("lgpl3_name", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("mpl2_name", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("bsd_grant", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"),
    ("bsd_source", "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."),
    ("bsd_binary", "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."),
    ("bsd_names", "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."),
    ("ccbync4_name", "Licensed under CC BY-NC 4.0."),
    ("ccbync4_name", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("ccby4_name", "Licensed under CC BY 4.0."),
    ("ccby4_name", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("ccbysa4_name", "Licensed under CC BY-SA 4.0."),
    ("cc0_name", "Licensed under CC0 1.0."),
    ("unlicense", "This is free and unencumbered software released into the public domain."),
    ("agpl_free", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("agpl3_name", "Licensed under the GNU Affero General Public License, version 3."),
    ("gpl2_free", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("lgpl21_free", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version."),
    ("isc_grant", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("zero_grant", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted."),
    ("isc_disclaims", "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS."),
    ("zlib_as_is", "This software is provided 'as-is', without any express or implied warranty."),
    ("zlib_grant", "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:"),
    ("boost_name", "Distributed under the Boost Software License, Version 1.0."),
    ("epl2_name", "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at https://www.eclipse.org/legal/epl-2.0/"),
    ("artistic2_name", "Licensed under the Artistic License 2.0."),
    ("ofl_name", "This Font Software is licensed under the SIL Open Font License, Version 1.1."),
    ("bsd_ads", "All advertising materials mentioning features or use of this software must display the following acknowledgement:"),
    ("ncsa_grant", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal with the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"),
    ("postgresql_grant", "Permission to use, copy, modify, and distribute this software and its documentation for any purpose, without fee, and without a written agreement is hereby granted, provided that the above copyright notice and this paragraph and the following two paragraphs appear in all copies."),
    ("wtfpl_name", "This program is free software. It comes without any warranty, to the extent permitted by applicable law."),
    ("eupl12_name", "Licensed under the EUPL, Version 1.2."),
    ("cddl1_name", "The contents of this file are subject to the terms of the Common Development and Distribution License, Version 1.0."),
    ("ccbynd4_name", "Licensed under CC BY-ND 4.0."),
    ("ccbyncsa4_name", "Licensed under CC BY-NC-SA 4.0."),
    ("ccbyncnd4_name", "Licensed under CC BY-NC-ND 4.0."),
    ("ccbysa3_name", "Licensed under CC BY-SA 3.0."),
    ("ccby3_name", "Licensed under CC BY 3.0."),
    ("odbl1_name", "This database is made available under the Open Database License: http://opendatacommons.org/licenses/odbl/1.0/"),
)

# Rules in the order in which they are tried, as (licence, identifiers in sequence).
RULES = (
    ("MIT", ("mit_name", "mit_grant", "mit_notice", "as_is")),
    ("MIT", ("mit_grant", "mit_notice", "as_is")),
    ("BSD-4-Clause", ("bsd_grant", "bsd_source", "bsd_binary", "bsd_ads", "bsd_names")),
    ("BSD-3-Clause", ("bsd_grant", "bsd_source", "bsd_binary", "bsd_names")),
    ("BSD-2-Clause", ("bsd_grant", "bsd_source", "bsd_binary")),
    ("Apache-2.0", ("apache2_name", "apache2_obtain", "apache2_limits")),
    ("GPL-3.0-or-later", ("gpl_free", "gpl_hope")),
    ("GPL-3.0-or-later", ("gpl_free",)),
    ("MIT", ("mit_name",)),
    ("Apache-2.0", ("apache2_name",)),
    ("GPL-3.0-only", ("gpl3_name",)),
    ("GPL-2.0-only", ("gpl2_name",)),
    ("LGPL-3.0-only", ("lgpl3_name",)),
    ("MPL-2.0", ("mpl2_name",)),
    ("CC-BY-NC-4.0", ("ccbync4_name",)),
    ("CC-BY-4.0", ("ccby4_name",)),
    ("CC-BY-SA-4.0", ("ccbysa4_name",)),
    ("CC0-1.0", ("cc0_name",)),
    ("Unlicense", ("unlicense",)),
    ("AGPL-3.0-or-later", ("agpl_free",)),
    ("AGPL-3.0-only", ("agpl3_name",)),
    ("GPL-2.0-or-later", ("gpl2_free",)),
    ("LGPL-2.1-or-later", ("lgpl21_free",)),
    ("ISC", ("isc_grant", "isc_disclaims")),
    ("0BSD", ("zero_grant", "isc_disclaims")),
    ("Zlib", ("zlib_as_is", "zlib_grant")),
    ("BSL-1.0", ("boost_name",)),
    ("EPL-2.0", ("epl2_name",)),
    ("Artistic-2.0", ("artistic2_name",)),
    ("OFL-1.1", ("ofl_name",)),
    ("NCSA", ("ncsa_grant",)),
    ("PostgreSQL", ("postgresql_grant",)),
    ("WTFPL", ("wtfpl_name",)),
    ("EUPL-1.2", ("eupl12_name",)),
    ("CDDL-1.0", ("cddl1_name",)),
    ("CC-BY-ND-4.0", ("ccbynd4_name",)),
    ("CC-BY-NC-SA-4.0", ("ccbyncsa4_name",)),
    ("CC-BY-NC-ND-4.0", ("ccbyncnd4_name",)),
    ("CC-BY-SA-3.0", ("ccbysa3_name",)),
    ("CC-BY-3.0", ("ccby3_name",)),
    ("ODbL-1.0", ("odbl1_name",)),
)

# Every sentence above holds one of these.
ANCHORS = ("licen", "permission", "warrant", "redistribut", "copyright", "public domain", "advertising", "eupl")

# Tags that name a licence of the rules are sentences with a rule of their own.
TAGS = tuple((f"spdx_{name}", f"SPDX-License-Identifier: {name}") for name in dict.fromkeys(name for name, _ in RULES))
SENTENCES += TAGS
RULES += tuple((key.removeprefix("spdx_"), (key,)) for key, _ in TAGS)


def normal(sentence: str) -> str:
    return re.sub("[^a-z0-9]+", " ", sentence.lower()).strip(" ")


def normalised(sentence: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(sentence), "[^a-z0-9]+", " "))


def spread(sentence: str) -> tuple[str, str]:
    """A pattern of a sentence whose words may stand on several lines, from a start to an end of a sentence, and the words on one line.

    Between two words there is no stop but where the sentence itself has one; comment marks count as white space.
    """
    words = re.findall("[A-Za-z0-9]+", sentence)
    gaps = re.findall("[^A-Za-z0-9]+", sentence.strip(" .:"))
    between = [r"[^A-Za-z0-9]++" if re.search("[.!?:]", g) else r"[^A-Za-z0-9.!?:]++" for g in gaps]
    body = words[0] + "".join(g + w for g, w in zip(between, words[1:]))
    return rf"(?i)(?<=\A|\n|[.!?:][ \t\r])[^A-Za-z0-9\n]*+{body}(?=[^A-Za-z0-9\n]*+(?:\n|\z)|[^A-Za-z0-9\s]*[.!?:][ \t\r])", " ".join(words)


def rejoined(text: Column, sentences=SENTENCES) -> Column:
    """The text with each known sentence on a line of its own, without the line breaks and stops that would cut it.

    Sentences are first sought as plain words in the normalised text; the patterns run only for those that are there, the longest first.
    """
    known = sorted(dict.fromkeys(s for _, s in sentences), key=lambda s: (-len(s), s))
    table = F.array(*[F.struct(F.lit(f" {normal(s)} ").alias("words"), F.lit(spread(s)[0]).alias("pattern"), F.lit(f"\n{spread(s)[1]}\n").alias("line")) for s in known])
    there = let(F.concat(F.lit(" "), normalised(text), F.lit(" ")), lambda words: F.filter(table, lambda s: F.contains(words, s["words"])))
    return F.aggregate(there, text, lambda acc, s: F.regexp_replace(acc, s["pattern"], s["line"]))


def sentences_of(text: Column) -> Column:
    """Lines, cut after a stop, a question mark, an exclamation mark or a colon that white space follows."""
    return F.split(F.regexp_replace(text, r"([.!?:])[ \t\r]+", "$1\n"), "\n", -1)


def scan(docs: DataFrame, id_col: str = "doc_id", text: str = "text", sentences=SENTENCES, rules=RULES, anchors=ANCHORS) -> DataFrame:
    """(doc_id, n_sentences, sentence_ids, licenses, n_licenses).

    ``sentence_ids``: identifiers found, in text order, comma-joined; ``licenses``: licences of the rules met, in rule order, each once, comma-joined;
    ``n_licenses`` counts rule matches, repeats included.
    """
    for _, s in sentences:
        if not any(a in s.lower() for a in anchors):
            raise ValueError(f"no anchor in {s!r}")
    known = F.create_map(*[F.lit(x) for x in {normal(s): k for k, s in sentences}.items() for x in x])
    lower = F.lower(F.col(text))
    likely = F.coalesce(F.greatest(*[lower.rlike(a.replace(" ", "[^a-z0-9]+")) if " " in a else F.contains(lower, F.lit(a)) for a in anchors]), F.lit(False))
    has_anchor = lambda s: F.greatest(*[F.contains(F.lower(s), F.lit(a)) for a in anchors])
    ids = F.filter(F.transform(F.filter(sentences_of(rejoined(F.col(text), sentences)), has_anchor), lambda s: F.try_element_at(known, normalised(s))), lambda k: k.isNotNull())
    found = docs.select(F.col(id_col).alias("doc_id"), F.when(likely, ids).otherwise(F.array().cast("array<string>")).alias("ids"))

    def use(acc: Column, rule: Column) -> Column:
        """A rule takes every place where its sequence stands; what is taken becomes a gap that no later rule spans."""
        sequence = F.concat(F.lit(","), F.array_join(rule["ids"], ",,"), F.lit(","))
        rest = F.replace(acc["rest"], sequence, F.lit("|"))
        n = F.floor((F.length(acc["rest"]) - F.length(rest)) / (F.length(sequence) - 1)).cast("long")
        return F.struct(rest.alias("rest"), F.when(n > 0, F.concat(acc["names"], F.array(rule["name"]))).otherwise(acc["names"]).alias("names"), (acc["n"] + n).alias("n"))

    table = F.array(*[F.struct(F.lit(name).alias("name"), F.array(*map(F.lit, seq)).alias("ids")) for name, seq in rules])
    begin = F.struct(F.array_join(F.transform("ids", lambda k: F.concat(F.lit(","), k, F.lit(","))), "").alias("rest"), F.array().cast("array<string>").alias("names"), F.lit(0).cast("long").alias("n"))
    met = F.when(F.size("ids") > 0, F.aggregate(table, begin, use))
    return found.withColumn("met", met).select(
        "doc_id",
        F.size("ids").cast("long").alias("n_sentences"),
        F.array_join("ids", ",").alias("sentence_ids"),
        F.coalesce(F.array_join(F.array_distinct("met.names"), ","), F.lit("")).alias("licenses"),
        F.coalesce("met.n", F.lit(0)).cast("long").alias("n_licenses"),
    )
