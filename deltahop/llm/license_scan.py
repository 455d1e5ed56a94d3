"""License scans: sentence-rule recognition with DataFrame functions only.

Known licence sentences are found in the normalised text; the identifier sequence of a document is then matched against
ordered licence rules. Line breaks, comment marks and the signs `;` and `:` may lie inside a known sentence; blank lines and the other
end signs may not. A known sentence may be the tail of a longer one (titles may not) and ends with its sentence or line; of several
at a place the longest counts. Positions count signs and line breaks; a line that goes on in lower case belongs to the one before it.

The SQL looks up whole sentences, so it equals the query on texts without carriage returns whose known sentences stand unwrapped.

Defined results: null and empty texts match nothing; every row is matched by itself, also where rows repeat an id; documents
without any match give no row; ties between rules give a row each; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

# Known licence sentences, normalised to lower-case letters and digits with single spaces.
SENTENCES = {
    "mit_release": "released under the mit license",
    "mit_licensed": "licensed under the mit license",
    "mit_title": "the mit license",
    "mit_title_short": "mit license",
    "mit_grant": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions",
    "mit_notice": "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    "mit_warranty": "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement",
    "mit_liability": "in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software",
    "apache_short": "licensed under the apache license version 2 0",
    "apache_header": "licensed under the apache license version 2 0 the license",
    "apache_use": "you may not use this file except in compliance with the license",
    "apache_copy": "you may obtain a copy of the license at",
    "apache_basis": "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    "apache_see": "see the license for the specific language governing permissions and limitations under the license",
    "gpl3_short": "this work is licensed under the gnu general public license version 3",
    "gpl_free": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    "gpl2_free": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version",
    "gpl_hope": "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    "gpl_details": "see the gnu general public license for more details",
    "gpl_copy": "you should have received a copy of the gnu general public license along with this program",
    "bsd_redistribution": "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    "bsd_source": "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
    "bsd_binary": "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution",
    "bsd_endorse": "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    "bsd_warranty": "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed",
    "cc_by_nc": "licensed under cc by nc 4 0",
    "cc_by": "licensed under cc by 4 0",
    "cc_by_sa": "licensed under cc by sa 4 0",
    "cc0": "this work has been dedicated to the public domain",
    "lgpl3_free": "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    "lgpl21_free": "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 2 1 of the license or at your option any later version",
    "lgpl_hope": "this library is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    "lgpl_details": "see the gnu lesser general public license for more details",
    "agpl_free": "this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    "agpl_details": "see the gnu affero general public license for more details",
    "mpl2_subject": "this source code form is subject to the terms of the mozilla public license v",
    "mpl2_copy": "if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0",
    "mpl2_copy_https": "if a copy of the mpl was not distributed with this file you can obtain one at https mozilla org mpl 2 0",
    "isc_grant": "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    "bsd0_grant": "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted",
    "isc_warranty": "the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness",
    "isc_liability": "in no event shall the author be liable for any special direct indirect or consequential damages or any damages whatsoever resulting from loss of use data or profits whether in an action of contract negligence or other tortious action arising out of or in connection with the use or performance of this software",
    "unlicense_free": "this is free and unencumbered software released into the public domain",
    "unlicense_anyone": "anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary for any purpose commercial or non commercial and by any means",
    "zlib_warranty": "this software is provided as is without any express or implied warranty",
    "zlib_liability": "in no event will the authors be held liable for any damages arising from the use of this software",
    "zlib_grant": "permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions",
    "boost_line": "distributed under the boost software license version 1 0",
    "boost_grant": "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license the software to use reproduce display distribute execute and transmit the software and to prepare derivative works of the software and to permit third parties to whom the software is furnished to do so all subject to the following",
    "epl2": "this program and the accompanying materials are made available under the terms of the eclipse public license 2 0 which is available at https www eclipse org legal epl 2 0",
    "bsd_line": "licensed under the bsd license",
    "bsd2_line": "licensed under the bsd 2 clause license",
    "bsd3_line": "licensed under the bsd 3 clause license",
    "isc_line": "licensed under the isc license",
    "mpl2_line": "licensed under the mozilla public license version 2 0",
    "gpl2_line": "licensed under the gnu general public license version 2",
    "lgpl3_line": "licensed under the gnu lesser general public license version 3",
    "agpl3_line": "licensed under the gnu affero general public license version 3",
    "epl2_line": "licensed under the eclipse public license 2 0",
}
# Ordered rules (licence, sentence identifiers in order).
RULES = {
    "apache-notice": ("Apache-2.0", ["apache_header", "apache_use", "apache_copy", "apache_basis", "apache_see"]),
    "apache-line": ("Apache-2.0", ["apache_short"]),
    "mit-text": ("MIT", ["mit_grant", "mit_notice", "mit_warranty", "mit_liability"]),
    "mit-title": ("MIT", ["mit_title"]),
    "mit-title-short": ("MIT", ["mit_title_short"]),
    "mit-line": ("MIT", ["mit_release"]),
    "mit-licensed-line": ("MIT", ["mit_licensed"]),
    "gpl3-notice": ("GPL-3.0-or-later", ["gpl_free", "gpl_hope", "gpl_details"]),
    "gpl2-notice": ("GPL-2.0-or-later", ["gpl2_free", "gpl_hope", "gpl_details"]),
    "gpl3-line": ("GPL-3.0", ["gpl3_short"]),
    "bsd2-text": ("BSD-2-Clause", ["bsd_redistribution", "bsd_source", "bsd_binary", "bsd_warranty"]),
    "bsd3-text": ("BSD-3-Clause", ["bsd_redistribution", "bsd_source", "bsd_binary", "bsd_endorse", "bsd_warranty"]),
    "cc-by-nc-line": ("CC-BY-NC-4.0", ["cc_by_nc"]),
    "cc-by-line": ("CC-BY-4.0", ["cc_by"]),
    "cc-by-sa-line": ("CC-BY-SA-4.0", ["cc_by_sa"]),
    "cc0-line": ("CC0-1.0", ["cc0"]),
    "lgpl3-notice": ("LGPL-3.0-or-later", ["lgpl3_free", "lgpl_hope", "lgpl_details"]),
    "lgpl21-notice": ("LGPL-2.1-or-later", ["lgpl21_free", "lgpl_hope", "lgpl_details"]),
    "agpl3-notice": ("AGPL-3.0-or-later", ["agpl_free", "gpl_hope", "agpl_details"]),
    "mpl2-notice": ("MPL-2.0", ["mpl2_subject", "mpl2_copy"]),
    "mpl2-notice-https": ("MPL-2.0", ["mpl2_subject", "mpl2_copy_https"]),
    "isc-text": ("ISC", ["isc_grant", "isc_warranty", "isc_liability"]),
    "bsd0-text": ("0BSD", ["bsd0_grant", "isc_warranty", "isc_liability"]),
    "unlicense-text": ("Unlicense", ["unlicense_free", "unlicense_anyone"]),
    "zlib-text": ("Zlib", ["zlib_warranty", "zlib_liability", "zlib_grant"]),
    "boost-line": ("BSL-1.0", ["boost_line"]),
    "boost-text": ("BSL-1.0", ["boost_grant"]),
    "epl2-notice": ("EPL-2.0", ["epl2"]),
    "bsd-line": ("BSD", ["bsd_line"]),
    "bsd2-line": ("BSD-2-Clause", ["bsd2_line"]),
    "bsd3-line": ("BSD-3-Clause", ["bsd3_line"]),
    "isc-line": ("ISC", ["isc_line"]),
    "mpl2-line": ("MPL-2.0", ["mpl2_line"]),
    "gpl2-line": ("GPL-2.0", ["gpl2_line"]),
    "lgpl3-line": ("LGPL-3.0", ["lgpl3_line"]),
    "agpl3-line": ("AGPL-3.0", ["agpl3_line"]),
    "epl2-line": ("EPL-2.0", ["epl2_line"]),
}
# Identifiers that stand in identifier lines, and the variants of the attribution licences.
IDENTIFIERS = "MIT Apache-2.0 BSD-2-Clause BSD-3-Clause ISC 0BSD MPL-2.0 GPL-2.0 GPL-2.0-only GPL-2.0-or-later GPL-3.0 GPL-3.0-only GPL-3.0-or-later LGPL-2.1-only LGPL-2.1-or-later LGPL-3.0-only LGPL-3.0-or-later AGPL-3.0-only AGPL-3.0-or-later Unlicense Zlib BSL-1.0 EPL-2.0 CC0-1.0 CC-BY-4.0 CC-BY-SA-4.0 Artistic-2.0 PostgreSQL".split()
VARIANTS = {"BY": "attribution", "BY-SA": "attribution sharealike", "BY-NC": "attribution noncommercial", "BY-ND": "attribution noderivatives", "BY-NC-SA": "attribution noncommercial sharealike", "BY-NC-ND": "attribution noncommercial noderivatives"}

for _id in IDENTIFIERS:
    _name = "id_" + "".join(c if c.isalnum() else "_" for c in _id.lower())
    SENTENCES[_name] = "spdx license identifier " + " ".join(_id.lower().replace("-", " ").replace(".", " ").split())
    RULES[_name.replace("_", "-")] = (_id, [_name])
for _code, _words in VARIANTS.items():
    for _article in ("a", "the"):
        _name = f"ccv4_{_code.lower().replace('-', '_')}_{_article}"
        SENTENCES[_name] = f"licensed under {_article} creative commons {_words} 4 0 international license"
        RULES[_name.replace("_", "-")] = (f"CC-{_code}-4.0", [_name])

TITLES = {"mit_title", "mit_title_short"}  # sentences that say nothing at the end of a longer one

IDENTIFIER_LINE = "(?i)(spdx-license-identifier:[^\\n]*)\\n"  # never goes on in the next line
WRAP = "\\n(?=[a-z])"
# Boundaries in the order they are marked: every one becomes one sign, so that signs before a sentence give its position.
HARD, LINE, COMMENT, WEAK = "\x01", "\x02", "\x03", "\x04"
BOUNDARIES = [
    ("(^|\\n)([ \\t]*)[;:!]+(?=[ \\n]|$)", f"$1$2{COMMENT}"),
    ("[;:]+(?=[ \\n]|$)(?<![.!?][;:]{1,9})", WEAK),
    ("[.;:!?]+(?=[ \\n]|$)", HARD),
    ("\\n\\n+", HARD),
    ("\\n", LINE),
]
NOISE = "[^a-z0-9\\x01-\\x04]+"
BLANK_LINE = "\\x02(?=[ \\x03]*\\x02)"
GAP = "[ \\x02-\\x04]+"


def normalised(text):
    """Lower-case letters and digits with single spaces, and a sign for every boundary."""
    out = F.regexp_replace(F.regexp_replace(text, "\\r\\n?", "\n"), IDENTIFIER_LINE, "$1\n\n")
    out = F.regexp_replace(out, WRAP, " ")
    for pattern, sign in BOUNDARIES:
        out = F.regexp_replace(out, pattern, sign)
    return F.regexp_replace(F.regexp_replace(F.lower(out), NOISE, " "), BLANK_LINE, HARD)


def known_pattern(sentences: dict[str, str]) -> str:
    """Matches the longest known sentence at a place."""
    ordered = sorted(sentences.items(), key=lambda x: (-len(x[1]), x[0]))
    alternatives = "|".join(("(?<=^|[\\x01-\\x04]|[\\x01-\\x04] )" if name in TITLES else "") + GAP.join(text.split()) for name, text in ordered)
    return f"(?<![a-z0-9])(?:{alternatives})(?= ?(?:[\\x01-\\x04]|\\z))"


def telling_words(sentences: dict[str, str]) -> list[str]:
    """Words of which every known sentence holds one: texts without any need no further look."""
    left, out = {name: set(text.split()) for name, text in sentences.items()}, []
    while left:
        words = sorted({w for s in left.values() for w in s if len(w) >= min(7, max(map(len, s)))})
        best = max(words, key=lambda w: (sum(w in s for s in left.values()), len(w)))
        out.append(best)
        left = {name: s for name, s in left.items() if best not in s}
    return out


def known_sentences(spark: SparkSession, sentences: dict[str, str]) -> DataFrame:
    return spark.createDataFrame(sorted((text, name) for name, text in sentences.items()), "sentence string, sentence_id string")


def license_rules(spark: SparkSession, rules: dict) -> DataFrame:
    return spark.createDataFrame([(name, spdx, steps, steps[0]) for name, (spdx, steps) in sorted(rules.items())], "rule string, license string, steps array<string>, sentence_id string")


def scan_sentences(docs: DataFrame, sentences: dict[str, str] | None = None) -> DataFrame:
    """(doc_id, row_key, pos, sentence_id): known sentences of each row in order; row_key tells rows of one id apart."""
    sentences = {name: text for name, text in (SENTENCES if sentences is None else sentences).items() if text.split()}
    spark = docs.sparkSession
    known = known_pattern(sentences) if sentences else "(?!)"
    likely = docs.where(F.lower("text").rlike("|".join(telling_words(sentences)) or "(?!)"))
    texts = likely.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.monotonically_increasing_id().alias("row_key"), normalised(F.col("text")).alias("line"))
    found = texts.select("doc_id", "row_key", F.regexp_extract_all("line", F.lit(known), F.lit(0)).alias("found"), F.split("line", known).alias("between")).where(F.size("found") > 0)
    each = found.select("doc_id", "row_key", F.posexplode(F.arrays_zip(F.slice("between", F.lit(1), F.size("found")).alias("before"), F.col("found").alias("raw"))).alias("k", "x"))
    signs = lambda text: F.length(F.regexp_replace(text, "[^\\x01-\\x04]", ""))
    so_far = F.sum(signs(F.col("x.before")) + signs(F.col("x.raw"))).over(Window.partitionBy("row_key").orderBy("k"))
    named = each.select("doc_id", "row_key", (so_far - signs(F.col("x.raw"))).cast("int").alias("pos"), F.regexp_replace("x.raw", GAP, " ").alias("sentence"))
    return named.join(F.broadcast(known_sentences(spark, sentences)), "sentence").select("doc_id", "row_key", "pos", "sentence_id")


def scan_licenses(docs: DataFrame, sentences: dict[str, str] | None = None, rules: dict | None = None) -> DataFrame:
    """(doc_id, rule, license, n_steps, first_pos, n_known): every rule whose sentences occur in order in a document.

    The tables of sentences and rules are fixed values of some hundred rows at most, so they are broadcast. A null doc_id is an
    id like any other.
    """
    rules = RULES if rules is None else rules
    found = scan_sentences(docs, sentences)
    sequence = found.groupBy("doc_id", "row_key").agg(F.array_sort(F.collect_list(F.struct("pos", "sentence_id"))).alias("seq"))
    starts = sequence.withColumn("sentence_id", F.explode(F.array_distinct(F.col("seq.sentence_id"))))
    tried = starts.join(F.broadcast(license_rules(docs.sparkSession, rules)), "sentence_id")
    reached = F.aggregate(
        "seq",
        F.struct(F.lit(0).alias("step"), F.lit(-1).alias("first")),
        lambda acc, x: F.when(
            F.get("steps", acc["step"]) == x["sentence_id"],
            F.struct((acc["step"] + 1).alias("step"), F.when(acc["step"] == 0, x["pos"]).otherwise(acc["first"]).alias("first")),
        ).otherwise(acc),
    )
    done = tried.withColumn("reached", reached).where(F.col("reached.step") == F.size("steps"))
    return done.select("doc_id", "rule", "license", F.size("steps").cast("bigint").alias("n_steps"), F.col("reached.first").cast("bigint").alias("first_pos"), F.size("seq").cast("bigint").alias("n_known"))


def oracle() -> str:
    """The same result in DuckDB SQL."""
    quote = lambda s: "'" + s.replace("'", "''") + "'"
    known = ", ".join(f"({quote(t)}, {quote(n)})" for n, t in sorted(SENTENCES.items()))
    steps = ", ".join(f"({quote(r)}, {quote(spdx)}, {k}, {quote(s)}, {len(names)})" for r, (spdx, names) in sorted(RULES.items()) for k, s in enumerate(names))
    return f"""
WITH RECURSIVE known(sentence, sentence_id) AS (VALUES {known}),
steps(rule, license, k, sentence_id, n_steps) AS (VALUES {steps}),
-- this dialect's patterns have no look-ahead: the sign after a boundary is put back by a doubled mark
marked AS (SELECT doc_id, regexp_replace(regexp_replace(text, '\\n([a-z])', ' \\1', 'g'), '([.;:!?]+)([ \\n]|$)', chr(1) || '\\2', 'g') AS t FROM documents),
parts AS (SELECT doc_id, unnest(regexp_split_to_array(t, '\\x01|\\n+')) AS raw, generate_subscripts(regexp_split_to_array(t, '\\x01|\\n+'), 1) - 1 AS pos FROM marked),
named AS (SELECT doc_id, pos, trim(regexp_replace(lower(raw), '[^a-z0-9]+', ' ', 'g')) AS sentence FROM parts),
hits AS (SELECT doc_id, pos, sentence_id FROM named JOIN known USING (sentence)),
counted AS (SELECT doc_id, count(*) AS n_known FROM hits GROUP BY doc_id),
walk AS (
  SELECT h.doc_id, s.rule, s.license, s.n_steps, 1 AS done, min(h.pos) AS first_pos, min(h.pos) AS at FROM hits h JOIN steps s ON s.k = 0 AND s.sentence_id = h.sentence_id GROUP BY ALL
  UNION ALL
  SELECT w.doc_id, w.rule, w.license, w.n_steps, w.done + 1, w.first_pos, (SELECT min(h.pos) FROM hits h WHERE h.doc_id = w.doc_id AND h.sentence_id = s.sentence_id AND h.pos > w.at)
  FROM walk w JOIN steps s ON s.rule = w.rule AND s.k = w.done WHERE w.at IS NOT NULL
)
SELECT w.doc_id, w.rule, w.license, CAST(w.n_steps AS BIGINT) AS n_steps, CAST(w.first_pos AS BIGINT) AS first_pos, CAST(c.n_known AS BIGINT) AS n_known
FROM walk w JOIN counted c USING (doc_id) WHERE w.done = w.n_steps AND w.at IS NOT NULL
"""
