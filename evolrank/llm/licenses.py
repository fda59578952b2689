"""License scan: known sentences become identifiers, identifier sequences are matched to rules.

Texts are cut into pieces at line ends (lines without words fall away) and after full stops; a piece is
normalised to its lower-cased words, so comment marks go.  A known sentence is
found where neighbouring pieces, at most ``MOST_PIECES``, put together are that
sentence: wrapped lines and sentences on one line both count.  Identifiers of a
document, in order, are then matched against rules: a rule holds if its
identifiers occur in that order with at most ``MOST_GAP`` foreign pieces between
neighbours.  Only texts with the longest word of some known sentence are cut,
and only documents with a known sentence reach the shuffle.

Defined results: null and empty texts and documents without a licence give no
row; a rule is reported once per document with its first place and number of
times; rows with a null id take no part; other columns are ignored.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, table, text_of

MOST_GAP = 3
MOST_PIECES = 40

# Licence sentences in public use, and the ordered rules over them.
SENTENCES = {
    "apache_notice": "Licensed under the Apache License, Version 2.0.",
    "apache_grant": "You may not use this file except in compliance with the License.",
    "apache_copy": "You may obtain a copy of the License at",
    "apache_basis": "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    "mit_notice": "Released under the MIT License.",
    "mit_grant": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "mit_keep": "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "as_is": "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT.",
    "gpl_notice": "This work is licensed under the GNU General Public License, version 3.",
    "gpl_free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "gpl_hope": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.",
    "bsd_grant": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "bsd_source": "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "bsd_binary": "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "cc_by_nc": "Licensed under CC BY-NC 4.0.",
    "cc_by": "Licensed under CC BY 4.0.",
    "cc_by_sa": "Licensed under CC BY-SA 4.0.",
    "mpl_notice": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "bsd_names": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    "isc_grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "gpl2_free": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    "lgpl_free": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.",
    "unlicense": "This is free and unencumbered software released into the public domain.",
    "agpl_free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "lgpl3_free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "epl_notice": "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at",
    "bsl_notice": "Distributed under the Boost Software License, Version 1.0.",
    "zlib_as_is": "This software is provided 'as-is', without any express or implied warranty.",
    "zlib_grant": "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:",
    "zero_grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.",
    "ofl_notice": "This Font Software is licensed under the SIL Open Font License, Version 1.1.",
    "cc0_notice": "To the extent possible under law, the author(s) have dedicated all copyright and related and neighboring rights to this software to the public domain worldwide.",
    "eupl_notice": "Licensed under the EUPL, Version 1.2 or - as soon they will be approved by the European Commission - subsequent versions of the EUPL (the \"Licence\");",
    "gpl2_notice": "This work is licensed under the GNU General Public License, version 2.",
    "cc_by_nd": "Licensed under CC BY-ND 4.0.",
    "cc_by_nc_sa": "Licensed under CC BY-NC-SA 4.0.",
    "cc_by_nc_nd": "Licensed under CC BY-NC-ND 4.0.",
}
# Other published forms of the same sentences.
FORMS = [
    ("apache_notice", "Licensed under the Apache License, Version 2.0 (the \"License\");"),
    ("epl_notice", "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at https://www.eclipse.org/legal/epl-2.0/"),
    ("cc_by", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("cc_by_sa", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("cc_by_nd", "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License."),
    ("cc_by_nc", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("cc_by_nc_sa", "This work is licensed under a Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License."),
    ("cc_by_nc_nd", "This work is licensed under a Creative Commons Attribution-NonCommercial-NoDerivatives 4.0 International License."),
]
RULES = {
    "Apache-2.0 notice": ("apache_notice",),
    "Apache-2.0 header": ("apache_notice", "apache_grant", "apache_basis"),
    "MIT notice": ("mit_notice",),
    "MIT text": ("mit_grant", "mit_keep", "as_is"),
    "GPL-3.0 notice": ("gpl_notice",),
    "GPL-3.0 header": ("gpl_free", "gpl_hope"),
    "BSD-2-Clause text": ("bsd_grant", "bsd_source", "bsd_binary"),
    "BSD-3-Clause text": ("bsd_grant", "bsd_source", "bsd_binary", "bsd_names"),
    "ISC text": ("isc_grant",),
    "GPL-2.0 header": ("gpl2_free", "gpl_hope"),
    "LGPL-2.1 header": ("lgpl_free",),
    "CC-BY-NC-4.0 notice": ("cc_by_nc",),
    "CC-BY-4.0 notice": ("cc_by",),
    "CC-BY-SA-4.0 notice": ("cc_by_sa",),
    "MPL-2.0 notice": ("mpl_notice",),
    "Unlicense": ("unlicense",),
    "AGPL-3.0 header": ("agpl_free", "gpl_hope"),
    "LGPL-3.0 header": ("lgpl3_free", "gpl_hope"),
    "EPL-2.0 notice": ("epl_notice",),
    "BSL-1.0 notice": ("bsl_notice",),
    "Zlib text": ("zlib_as_is", "zlib_grant"),
    "0BSD text": ("zero_grant",),
    "OFL-1.1 notice": ("ofl_notice",),
    "CC0-1.0 notice": ("cc0_notice",),
    "EUPL-1.2 notice": ("eupl_notice",),
    "GPL-2.0 notice": ("gpl2_notice",),
    "CC-BY-ND-4.0 notice": ("cc_by_nd",),
    "CC-BY-NC-SA-4.0 notice": ("cc_by_nc_sa",),
    "CC-BY-NC-ND-4.0 notice": ("cc_by_nc_nd",),
}
# Licences whose published short identifier stands in a marked line.
IDENTIFIERS = ["Apache-2.0", "MIT", "BSD-2-Clause", "BSD-3-Clause", "ISC", "GPL-2.0-only", "GPL-2.0-or-later", "GPL-3.0-only", "GPL-3.0-or-later", "LGPL-2.1-only", "LGPL-2.1-or-later", "LGPL-3.0-only", "LGPL-3.0-or-later", "AGPL-3.0-only", "AGPL-3.0-or-later", "MPL-2.0", "EPL-2.0", "EUPL-1.2", "BSL-1.0", "Zlib", "0BSD", "Unlicense", "CC0-1.0", "CC-BY-4.0", "CC-BY-SA-4.0", "OFL-1.1"]
SENTENCES |= {f"id_{name}": f"SPDX-License-Identifier: {name}" for name in IDENTIFIERS}
RULES |= {f"{name} identifier": (f"id_{name}",) for name in IDENTIFIERS}
WIDER = {"BSD-2-Clause text": "BSD-3-Clause text"}  # not reported where the wider rule holds from the same place
CUT = r"\n[^\p{L}\p{N}]*\n|\n|(?<=[.!?:;])[ \t]+(?=[\p{Lu}\"'(])|(?<=\"License\"\);)[ \t]+|(?<=LICENSE-2\.0)[ \t]+"


def normalised(sentence: Column) -> Column:
    return F.btrim(F.regexp_replace(F.lower(sentence), r"[^\p{L}\p{N}]+", " "))


def known_sentences(spark: SparkSession) -> DataFrame:
    """(first, known, sentence): the first word, all words and the name of each known sentence."""
    rows = spark.createDataFrame([*SENTENCES.items(), *FORMS], "sentence string, body string").withColumn("known", normalised(F.col("body")))
    return rows.select(F.substring_index("known", " ", 1).alias("first"), "known", "sentence")


def telling_words() -> list[str]:
    """The longest word of every known sentence: a text without any of them holds none of the sentences."""
    longest = {max(re.findall(r"[a-z0-9]+", body.lower()), key=len) for body in [*SENTENCES.values(), *(b for _, b in FORMS)]}
    return sorted(w for w in longest if not any(v != w and v in w for v in longest))


def may_hold(text: Column) -> Column:
    """Whether a text has a telling word; the class of their first letters passes most places by."""
    words = telling_words()
    return F.lower(text).rlike(f"(?=[{''.join(sorted({w[0] for w in words}))}])(?:{'|'.join(words)})")


def sentence_hits(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(d, at, to, sentence): first and last piece of every sentence of a document that a licence is known to have."""
    text = text_of(docs, text_col)
    cut = docs.where(docs[id_col].isNotNull() & may_hold(text)).select(docs[id_col].alias("d"), F.split(text, CUT).alias("pieces"))
    opening = F.transform("pieces", lambda p: normalised(F.substring(F.regexp_replace(p, r"^[^\p{L}\p{N}]+", ""), 1, 60)))
    spread = cut.select("d", "pieces", F.posexplode_outer(opening).alias("at", "s"))  # outer: no filter that would cut the text once more
    known = F.broadcast(known_sentences(docs.sparkSession))  # as many rows as this module states
    begun = spread.where("s != ''").withColumn("first", F.substring_index("s", " ", 1)).join(known, "first")
    begun = begun.where(F.col("known").startswith(F.substring("s", 1, 40)))
    near = begun.select("d", "at", "known", "sentence", F.transform(F.slice("pieces", F.col("at") + 1, MOST_PIECES), normalised).alias("near"))
    words = lambda pieces: F.array_join(F.array_remove(pieces, ""), " ")
    likely = near.where(F.concat(words(F.col("near")), F.lit(" ")).startswith(F.concat("known", F.lit(" "))))
    last = F.get(F.filter(F.sequence(F.lit(1), F.size("near")), lambda k: words(F.slice("near", 1, k)) == F.col("known")), 0)  # null: the sentence ends within a piece
    return likely.withColumn("to", F.col("at") + last - 1).where("to is not null").groupBy("d", "at", "sentence").agg(F.min("to").alias("to")).select("d", "at", "to", "sentence")


def match_rules(hits: DataFrame) -> DataFrame:
    """(doc_id, license, n_matches, first_sentence) from identifier sequences.

    A rule of k sentences is a chain of k - 1 steps, each the next wanted
    identifier within the allowed gap; chains grow by joins on (document, place),
    so no document's identifiers are gathered into one value.
    """
    spark = hits.sparkSession
    hits = materialise(hits.distinct())  # every step of a chain reads them; the texts are cut and compared once
    steps = spark.createDataFrame([(r, i, s, len(seq)) for r, seq in RULES.items() for i, s in enumerate(seq)], "rule string, step int, sentence string, n_steps int")
    tagged = hits.join(F.broadcast(steps), "sentence").select("d", "at", "to", "rule", "step", "n_steps")
    chain = tagged.where("step = 0").select("d", "rule", "n_steps", F.col("at").alias("first_at"), F.col("to").alias("last_at"))
    ends = chain.where("n_steps = 1").select("d", "rule", "first_at")
    for step in range(1, max(map(len, RULES.values()))):
        nxt = tagged.where(F.col("step") == step).select("d", "rule", "at", "to")
        chain = (
            chain.where(F.col("n_steps") > step).join(nxt, ["d", "rule"])
            .where((F.col("at") > F.col("last_at")) & (F.col("at") <= F.col("last_at") + MOST_GAP + 1))
            .groupBy("d", "rule", "n_steps", "first_at").agg(F.min("to").alias("last_at"))
        )
        ends = ends.unionByName(chain.where(F.col("n_steps") == step + 1).select("d", "rule", "first_at"))
    wider = spark.createDataFrame(list(WIDER.items()), "narrow string, rule string")
    ends = ends.join(ends.join(F.broadcast(wider), "rule").select("d", F.col("narrow").alias("rule"), "first_at").distinct(), ["d", "rule", "first_at"], "left_anti")
    return ends.groupBy("d", "rule").agg(F.count(F.lit(1)).alias("n_matches"), F.min("first_at").cast("long").alias("first_sentence")).select(F.col("d").alias("doc_id"), F.col("rule").alias("license"), "n_matches", "first_sentence")


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    return match_rules(sentence_hits(docs, id_col, text_col))


def op4_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents").select("doc_id", "text"))
