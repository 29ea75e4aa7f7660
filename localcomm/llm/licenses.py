"""Licence scan by sentence rules, in DataFrame functions only.

Texts are normalised (lower case, runs of other characters than letters and digits become one blank) and known licence
sentences looked up in them. A sentence starts and ends at a line end, a blank line, a stop, colon or semicolon. It may
run over single line ends, with or without comment marks, and over colons, semicolons and the stop of "v."; stops and
blank lines always cut. Of sentences that start at one place the longest counts. The identifiers, in text order, form a sequence;
ordered rules then consume it, the longest grants first, and name the licences. The plan is one projection over
the scan: no shuffle, no Python.

Cases: null or empty text has no identifiers and no licence; a null id is kept; repeated rows give repeated results; an
empty table gives none; other columns are ignored; the order of
licences follows the rules, not the text; sentences that are cited twice count twice in `sentences`.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Public licence sentences after normalisation, with the identifiers used in the rules.
#: Each {v} stands for the versions listed with the sentence; the identifier carries the version.
SENTENCES: list[tuple[str, str, tuple[str, ...]]] = [
    ("released under the mit license", "MitRef", ()),
    ("licensed under the mit license", "MitRef", ()),
    ("this project is licensed under the mit license", "MitRef", ()),
    ("the mit license", "MitTitle", ()),
    ("mit license", "MitTitle", ()),
    ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions", "MitGrant", ()),
    ("the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software", "MitNotice", ()),
    ("the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement", "MitAsIs", ()),
    ("licensed under the apache license version {v}", "ApacheRef", ("2 0", "1 1")),
    ("licensed under the apache license version {v} the license", "ApacheRef", ("2 0", "1 1")),
    ("apache license version {v}", "ApacheRef", ("2 0", "1 1")),
    ("you may not use this file except in compliance with the license", "ApacheComply", ()),
    ("you may obtain a copy of the license at", "ApacheCopy", ()),
    ("unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied", "ApacheAsIs", ()),
    ("see the license for the specific language governing permissions and limitations under the license", "ApacheSee", ()),
    ("this work is licensed under the gnu general public license version {v}", "GplRef", ("2", "3")),
    ("licensed under the gnu general public license version {v}", "GplRef", ("2", "3")),
    ("gnu general public license version {v}", "GplRef", ("2", "3")),
    ("this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version {v} of the license or at your option any later version", "GplLater", ("2", "3")),
    ("this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose", "GplHope", ()),
    ("licensed under the gnu lesser general public license version {v}", "LgplRef", ("2 1", "3")),
    ("licensed under the gnu affero general public license version {v}", "AgplRef", ("3",)),
    ("licensed under cc by {v}", "CcByRef", ("2 0", "3 0", "4 0")),
    ("licensed under cc by sa {v}", "CcBySaRef", ("2 0", "3 0", "4 0")),
    ("licensed under cc by nc {v}", "CcByNcRef", ("2 0", "3 0", "4 0")),
    ("licensed under cc by nd {v}", "CcByNdRef", ("2 0", "3 0", "4 0")),
    ("licensed under cc by nc sa {v}", "CcByNcSaRef", ("2 0", "3 0", "4 0")),
    ("licensed under cc by nc nd {v}", "CcByNcNdRef", ("2 0", "3 0", "4 0")),
    ("licensed under cc0 {v}", "Cc0Ref", ("1 0",)),
    ("this work is dedicated to the public domain", "PublicDomain", ()),
    ("this is free and unencumbered software released into the public domain", "Unlicense", ()),
    ("redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met", "BsdGrant", ()),
    ("redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer", "BsdSource", ()),
    ("redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution", "BsdBinary", ()),
    ("neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission", "BsdNames", ()),
    ("licensed under the bsd {v} clause license", "BsdRef", ("2", "3")),
    ("this source code form is subject to the terms of the mozilla public license v 2 0", "MplRef", ()),
    ("licensed under the mozilla public license version 2 0", "MplRef", ()),
    ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies", "IscGrant", ()),
    ("all rights reserved", "AllRights", ()),
    ("in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software", "MitLiable", ()),
    ("this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed", "BsdAsIs", ()),
    ("in no event shall the copyright holder or contributors be liable for any direct indirect incidental special exemplary or consequential damages including but not limited to procurement of substitute goods or services loss of use data or profits or business interruption however caused and on any theory of liability whether in contract strict liability or tort including negligence or otherwise arising in any way out of the use of this software even if advised of the possibility of such damage", "BsdLiable", ()),
    ("the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness", "IscAsIs", ()),
    ("in no event shall the author be liable for any special direct indirect or consequential damages or any damages whatsoever resulting from loss of use data or profits whether in an action of contract negligence or other tortious action arising out of or in connection with the use or performance of this software", "IscLiable", ()),
    ("licensed under the isc license", "IscRef", ()),
    ("isc license", "IscRef", ()),
    ("this program is free software you can redistribute it and or modify it under the terms of the gnu general public license version {v} as published by the free software foundation", "GplOnly", ("2", "3")),
    ("see the gnu general public license for more details", "GplSee", ()),
    ("this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version {v} of the license or at your option any later version", "LgplLater", ("2 1", "3")),
    ("this program is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version {v} of the license or at your option any later version", "LgplLater", ("2 1", "3")),
    ("this library is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose", "LgplHope", ()),
    ("see the gnu lesser general public license for more details", "LgplSee", ()),
    ("gnu lesser general public license version {v}", "LgplRef", ("2 1", "3")),
    ("this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either version {v} of the license or at your option any later version", "AgplLater", ("3",)),
    ("see the gnu affero general public license for more details", "AgplSee", ()),
    ("gnu affero general public license version {v}", "AgplRef", ("3",)),
    ("if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0", "MplCopy", ()),
    ("if a copy of the mpl was not distributed with this file you can obtain one at https mozilla org mpl 2 0", "MplCopy", ()),
    ("mozilla public license version 2 0", "MplRef", ()),
    ("permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license the software to use reproduce display distribute execute and transmit the software and to prepare derivative works of the software and to permit third parties to whom the software is furnished to do so all subject to the following", "BoostGrant", ()),
    ("distributed under the boost software license version 1 0", "BoostRef", ()),
    ("boost software license version 1 0", "BoostRef", ()),
    ("this software is provided as is without any express or implied warranty", "ZlibAsIs", ()),
    ("permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions", "ZlibGrant", ()),
    ("anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary for any purpose commercial or non commercial and by any means", "UnlicenseGrant", ()),
    ("this work is licensed under a creative commons attribution {v} international license", "CcByRef", ("4 0",)),
    ("this work is licensed under a creative commons attribution sharealike {v} international license", "CcBySaRef", ("4 0",)),
    ("this work is licensed under a creative commons attribution noncommercial {v} international license", "CcByNcRef", ("4 0",)),
    ("this work is licensed under a creative commons attribution noderivatives {v} international license", "CcByNdRef", ("4 0",)),
    ("eclipse public license version {v}", "EplRef", ("1 0", "2 0")),
    ("licensed under the eclipse public license version {v}", "EplRef", ("1 0", "2 0")),
]

#: Identifiers that may follow a short tag in a file's head, each its own sentence after normalisation.
TAGGED = ["MIT", "ISC", "Apache-2.0", "BSD-2-Clause", "BSD-3-Clause", "GPL-2.0-only", "GPL-2.0-or-later", "GPL-3.0-only", "GPL-3.0-or-later", "LGPL-2.1-only", "LGPL-2.1-or-later", "LGPL-3.0-only", "LGPL-3.0-or-later", "AGPL-3.0-only", "AGPL-3.0-or-later", "MPL-2.0", "BSL-1.0", "Zlib", "EPL-2.0", "CC0-1.0", "CC-BY-4.0", "CC-BY-SA-4.0", "Unlicense"]

#: Ordered rules over ",Id,Id," sequences: the earlier rule takes its identifiers before a later one looks.
RULES: list[tuple[str, str]] = [
    *[(f",Tag-{name.replace('.', '-')},", name) for name in TAGGED],
    (",MitGrant,MitNotice,(MitAsIs,)?(MitLiable,)?", "MIT"),
    (",IscGrant,(IscAsIs,)?(IscLiable,)?", "ISC"),
    (",BsdGrant,BsdSource,BsdBinary,BsdNames,(BsdAsIs,)?(BsdLiable,)?", "BSD-3-Clause"),
    (",BsdGrant,BsdSource,BsdBinary,(BsdAsIs,)?(BsdLiable,)?", "BSD-2-Clause"),
    (",(BoostRef,)?BoostGrant,", "BSL-1.0"),
    (",ZlibAsIs,ZlibGrant,", "Zlib"),
    (",Unlicense,(UnlicenseGrant,)?", "Unlicense"),
    (",MplRef,MplCopy,", "MPL-2.0"),
    (",ApacheRef-2-0,ApacheComply,ApacheCopy,ApacheAsIs,(ApacheSee,)?", "Apache-2.0"),
    (",AgplLater-3,(GplHope,)?(AgplSee,)?", "AGPL-3.0-or-later"),
    (",LgplLater-3,((GplHope|LgplHope),)?(LgplSee,)?", "LGPL-3.0-or-later"),
    (",LgplLater-2-1,((GplHope|LgplHope),)?(LgplSee,)?", "LGPL-2.1-or-later"),
    (",GplLater-3,(GplHope,)?(GplSee,)?", "GPL-3.0-or-later"),
    (",GplLater-2,(GplHope,)?(GplSee,)?", "GPL-2.0-or-later"),
    (",GplOnly-3,(GplHope,)?(GplSee,)?", "GPL-3.0-only"),
    (",GplOnly-2,(GplHope,)?(GplSee,)?", "GPL-2.0-only"),
    (",ApacheRef-2-0,", "Apache-2.0"),
    (",ApacheRef-1-1,", "Apache-1.1"),
    (",(MitRef|MitTitle),", "MIT"),
    (",GplRef-3,", "GPL-3.0-only"),
    (",GplRef-2,", "GPL-2.0-only"),
    (",LgplRef-3,", "LGPL-3.0-only"),
    (",LgplRef-2-1,", "LGPL-2.1-only"),
    (",AgplRef-3,", "AGPL-3.0-only"),
    (",MplRef,", "MPL-2.0"),
    (",IscRef,", "ISC"),
    (",BoostRef,", "BSL-1.0"),
    (",EplRef-2-0,", "EPL-2.0"),
    (",EplRef-1-0,", "EPL-1.0"),
    (",BsdRef-3,", "BSD-3-Clause"),
    (",BsdRef-2,", "BSD-2-Clause"),
    *[(f",Cc{k}Ref-{v}-0,", f"CC-{name}-{v}.0") for k, name in (("By", "BY"), ("BySa", "BY-SA"), ("ByNc", "BY-NC"), ("ByNd", "BY-ND"), ("ByNcSa", "BY-NC-SA"), ("ByNcNd", "BY-NC-ND")) for v in (4, 3, 2)],
    (",Cc0Ref-1-0,", "CC0-1.0"),
    (",PublicDomain,", "Public-Domain"),
]

#: Where a sentence ends for the SQL twin, which knows sentences on one line only: a line end, or a stop, colon or semicolon before a blank or the end.
SPLIT = r"\n|[.!?;:]+(?:[ \t\r\n]+|$)"
OTHER = r"[^a-z0-9]+"


def sentence_ids() -> dict[str, str]:
    out = {}
    for text, ident, versions in SENTENCES:
        for v in versions or ("",):
            out[text.replace("{v}", v)] = f"{ident}-{v.replace(' ', '-')}" if v else ident
    for name in TAGGED:
        out["spdx license identifier " + re.sub(OTHER, " ", name.lower())] = f"Tag-{name.replace('.', '-')}"
    return out


#: A text without any of these words holds no known sentence; found from the sentences themselves.
ANCHOR = r"licen|permission|anyone[^a-z0-9]+is|liable|disclaim|mpl|as[^a-z0-9]+is|copyright|redistribut|warrant|public[^a-z0-9]+domain|rights[^a-z0-9]+reserved"


#: Marks in a lower-case text, by order: line ends lose the comment marks after them; S cuts always, L may stand inside a sentence.
MARKS = [
    (r"\r\n?", "\n"),
    (r"\n[^a-z0-9\n]*", "\n"),
    (r"(?:(?<=\bv)[.]|[;:])(?:[ \t\n]++|$)(?<!\n\n)", "L"),
    (r"[.!?;:]+(?:[ \t\n]+|$)|\n\n+", "S"),
    (r"\n", "L"),
    (r"[^a-z0-9SL]+", " "),
    (r"[ L]*S[ LS]*", "S"),
    (r" ?L[ L]*", "L"),
]


def identified(text: Column) -> Column:
    """The identifiers of the known sentences of a text, in text order."""
    known = sentence_ids()
    table = F.create_map(*[F.lit(x) for kv in known.items() for x in kv])
    marked = F.lower(text)
    for pattern, mark in MARKS:
        marked = F.regexp_replace(marked, pattern, mark)
    any_of = "|".join(k.replace(" ", "[ L]") for k in sorted(known, key=len, reverse=True))
    found = F.regexp_extract_all(F.concat(F.lit("S"), F.trim(marked), F.lit("S")), F.lit(f"(?<=[SL])(?:{any_of})(?=[SL])"), F.lit(0))
    return F.transform(found, lambda s: table[F.translate(s, "L", " ")])


def scanned(documents: DataFrame) -> DataFrame:
    """doc_id, n_sentences, sentences (identifiers joined by a comma) and licenses (joined by a blank; empty if none)."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    seq = F.when(F.lower(text).rlike(ANCHOR + "|license"), identified(text)).otherwise(F.array().cast("array<string>"))
    rules = F.array(*[F.struct(F.lit(p).alias("pattern"), F.lit(n).alias("name")) for p, n in RULES])
    # Each identifier stands between its own two commas while rules consume them.
    start = F.struct(F.concat(F.lit(","), F.col("sentences"), F.lit(",")).alias("rest"), F.lit("").alias("names"))
    step = lambda acc, r: F.when(F.rlike(acc["rest"], r["pattern"]), F.struct(F.regexp_replace(acc["rest"], r["pattern"], F.lit(",")).alias("rest"), F.concat(acc["names"], F.lit(" "), r["name"]).alias("names"))).otherwise(acc)
    fold = F.aggregate(rules, start, step, lambda acc: F.ltrim(acc["names"]))
    return (
        documents.select(F.col("doc_id").cast("long").alias("doc_id"), seq.alias("ids"))
        .select("doc_id", F.size("ids").cast("long").alias("n_sentences"), F.array_join("ids", ",").alias("sentences"))
        .select("doc_id", "n_sentences", "sentences", F.when(F.col("n_sentences") > 0, fold).otherwise(F.lit("")).alias("licenses"))
    )


def op8_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scanned(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def oracle() -> str:
    """The same in DuckDB: a join to the table of sentences, then one CASE per rule in turn."""
    quote = lambda s: "'" + s.replace("'", "''") + "'"
    known = ", ".join(f"({quote(k)}, {quote(v)})" for k, v in sentence_ids().items())
    split = SPLIT.replace("(?:", "(").replace("\\n", "\n").replace("\\t", "\t").replace("\\r", "\r")
    ctes = [
        f"known(sentence, ident) AS (VALUES {known})",
        f"parts AS (SELECT rn, unnest(regexp_split_to_array(lower(text), {quote(split)})) AS part, unnest(range(len(regexp_split_to_array(lower(text), {quote(split)})))) AS place FROM base WHERE text IS NOT NULL)",
        f"hits AS (SELECT rn, place, ident FROM parts JOIN known ON sentence = trim(regexp_replace(part, {quote(OTHER)}, ' ', 'g')))",
        "seqs AS (SELECT rn, count(*) AS n, string_agg(ident, ',' ORDER BY place) AS sentences FROM hits GROUP BY rn)",
        "s0 AS (SELECT b.rn, b.doc_id, coalesce(n, 0) AS n_sentences, coalesce(sentences, '') AS sentences, ',' || coalesce(sentences, '') || ',' AS rest, '' AS names FROM base b LEFT JOIN seqs s ON s.rn = b.rn)",
    ]
    for i, (pattern, name) in enumerate(RULES):
        ctes.append(
            f"s{i + 1} AS (SELECT rn, doc_id, n_sentences, sentences, CASE WHEN regexp_matches(rest, {quote(pattern)}) THEN regexp_replace(rest, {quote(pattern)}, ',', 'g') ELSE rest END AS rest,"
            f" CASE WHEN regexp_matches(rest, {quote(pattern)}) THEN names || ' ' || {quote(name)} ELSE names END AS names FROM s{i})"
        )
    return "WITH base AS (SELECT row_number() OVER () AS rn, CAST(doc_id AS BIGINT) AS doc_id, text FROM documents), " + ", ".join(ctes) + f" SELECT doc_id, n_sentences, sentences, ltrim(names) AS licenses FROM s{len(RULES)}"
