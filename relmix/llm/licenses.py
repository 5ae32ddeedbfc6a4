"""Licence scans by sentence rules, on DataFrame functions only.

Texts are normalised (lower case, signs to blanks, blanks joined) and keep a mark wherever a sentence
may begin or end: at line ends, brackets, ``;``, and stops that white space follows. A known licence
sentence is found where its words stand between two marks, whatever marks are among them, so it may be
wrapped over lines (with comment signs before each) or hold a ``;`` or ``v. 2``; lines without a letter
or digit end every sentence. Per document the matched identifiers in order are compared with licence
rules: a rule is a sequence of identifiers that must occur in this order, with nothing but other
licence sentences between. A longer rule wins over the rules it contains.

The rule tables are constants of this module (under a hundred rows), so broadcasting them has a
proven bound. Documents without a word of every known sentence's choice (``ANCHORS``) are not
normalised, and those without a known sentence never leave the scan stage.

Defined cases: null, empty and licence-free texts give no rows;
repeated sentences keep every position; a null id forms one group of its
own in the sequence step, so ids should be present; repeated ids are one document.
"""

from __future__ import annotations

from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from relmix.llm.columns import narrow

#: Public licence sentences by identifier, normalised.
SENTENCES = {
    "mit.short": "released under the mit license",
    "mit.short2": "licensed under the mit license",
    "mit.grant": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions",
    "mit.notice": "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    "mit.warranty": "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement",
    "apache.short": "licensed under the apache license version 2 0",
    "apache.use": "you may not use this file except in compliance with the license",
    "apache.copy": "you may obtain a copy of the license at",
    "apache.dist": "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    "gpl3.short": "this work is licensed under the gnu general public license version 3",
    "gpl.free": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    "gpl2.free": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version",
    "gpl.hope": "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    "lgpl.short": "licensed under the gnu lesser general public license version 3",
    "agpl.short": "licensed under the gnu affero general public license version 3",
    "mpl2.form": "this source code form is subject to the terms of the mozilla public license v 2 0",
    "mpl2.copy": "if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0",
    "bsd.use": "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    "bsd.source": "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
    "bsd.binary": "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution",
    "bsd.endorse": "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    "bsd.warranty": "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed",
    "isc.grant": "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    "unlicense.free": "this is free and unencumbered software released into the public domain",
    "cc0.short": "licensed under cc0 1 0",
    "ccby.short": "licensed under cc by 4 0",
    "ccbysa.short": "licensed under cc by sa 4 0",
    "ccbync.short": "licensed under cc by nc 4 0",
    "ccbynd.short": "licensed under cc by nd 4 0",
    "ccbyncsa.short": "licensed under cc by nc sa 4 0",
    "ccby.work": "this work is licensed under a creative commons attribution 4 0 international license",
    "ccbysa.work": "this work is licensed under a creative commons attribution sharealike 4 0 international license",
    "ccbync.work": "this work is licensed under a creative commons attribution noncommercial 4 0 international license",
    "reserved": "all rights reserved",
}
#: Licence rules as ordered identifier sequences.
RULES = [
    ("MIT", ["mit.short"]),
    ("MIT", ["mit.short2"]),
    ("MIT", ["mit.grant"]),
    ("MIT", ["mit.grant", "mit.notice", "mit.warranty"]),
    ("Apache-2.0", ["apache.short"]),
    ("Apache-2.0", ["apache.short", "apache.use", "apache.copy", "apache.dist"]),
    ("GPL-3.0", ["gpl3.short"]),
    ("GPL-3.0-or-later", ["gpl.free"]),
    ("GPL-3.0-or-later", ["gpl.free", "gpl.hope"]),
    ("GPL-2.0-or-later", ["gpl2.free"]),
    ("GPL-2.0-or-later", ["gpl2.free", "gpl.hope"]),
    ("LGPL-3.0", ["lgpl.short"]),
    ("AGPL-3.0", ["agpl.short"]),
    ("MPL-2.0", ["mpl2.form"]),
    ("MPL-2.0", ["mpl2.form", "mpl2.copy"]),
    ("BSD-2-Clause", ["bsd.use", "bsd.source", "bsd.binary", "bsd.warranty"]),
    ("BSD-3-Clause", ["bsd.use", "bsd.source", "bsd.binary", "bsd.endorse", "bsd.warranty"]),
    ("ISC", ["isc.grant"]),
    ("Unlicense", ["unlicense.free"]),
    ("CC0-1.0", ["cc0.short"]),
    ("CC-BY-4.0", ["ccby.short"]),
    ("CC-BY-4.0", ["ccby.work"]),
    ("CC-BY-SA-4.0", ["ccbysa.short"]),
    ("CC-BY-SA-4.0", ["ccbysa.work"]),
    ("CC-BY-NC-4.0", ["ccbync.short"]),
    ("CC-BY-NC-4.0", ["ccbync.work"]),
    ("CC-BY-ND-4.0", ["ccbynd.short"]),
    ("CC-BY-NC-SA-4.0", ["ccbyncsa.short"]),
    ("all-rights-reserved", ["reserved"]),
]


#: Every known sentence has one of these parts of words; a word is never cut by a line's end.
ANCHORS = ("licen", "software", "warrant", "redistrib", "reserved", "mpl")
#: Marks are capitals, which lowered text does not have: S may be inside a sentence, H may not.
KNOWN = "(?<=[SH] )(?:" + "|".join(" (?:S )*+".join(norm.split()) for norm in SENTENCES.values()) + ")(?= [SH] )"


def marked(text: Column) -> Column:
    """Normalised words and the marks S and H, each between single blanks."""
    text = F.regexp_replace(F.lower(text), r"\r\n?", "\n")
    text = F.regexp_replace(text, r"(?m)^[^a-z0-9\n]*(?:dnl|rem)(?=\s)|(?<=http)s(?=:)", "")
    text = F.regexp_replace(text, r"\n[^a-z0-9\n]*(?=\n)", " H ")
    text = F.regexp_replace(text, r"[\n;()]|[.!?:]+(?=\s|$)", " S ")
    return F.concat(F.lit("S "), F.trim(F.regexp_replace(text, "[^a-z0-9SH]+", " ")), F.lit(" S "))


def license_hits(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, pos, sid): every known sentence with the number of marks before it."""
    spark = docs.sparkSession
    known = F.broadcast(spark.createDataFrame([(k, v) for k, v in SENTENCES.items()], "sid string, norm string"))
    rows = narrow(docs, id=id_col, text=text_col)
    low = F.lower("text")
    near = rows.filter(reduce(or_, [F.contains(low, F.lit(word)) for word in ANCHORS]))
    line = near.select("id", marked(F.col("text")).alias("line"))
    cut = line.select("id", F.split("line", KNOWN, -1).alias("gaps"), F.regexp_extract_all("line", F.lit(KNOWN), F.lit(0)).alias("found"))
    marks = lambda s: F.length(s) - F.length(F.translate(s, "SH", ""))
    upto = lambda i: marks(F.concat(F.array_join(F.slice("gaps", 1, i + 1), ""), F.array_join(F.slice("found", 1, i), "")))
    hits = cut.filter(F.size("found") > 0).select("id", "gaps", "found", F.posexplode("found").alias("nth", "raw"))
    return hits.select("id", upto(F.col("nth")).alias("pos"), F.replace("raw", F.lit("S "), F.lit("")).alias("norm")).join(known, "norm").select("id", "pos", "sid")


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_sentences, sequence, licenses) for every document with a known sentence.

    ``sequence`` is the ordered list of matched identifiers, ``licenses`` the sorted names of the rules
    that match and are not part of a longer matching rule.
    """
    hits = license_hits(docs, id_col, text_col)
    sequence = F.transform(F.array_sort(F.collect_list(F.struct("pos", "sid"))), lambda x: x["sid"])
    by_doc = hits.groupBy("id").agg(F.count(F.lit(1)).alias("n_sentences"), sequence.alias("sequence"))
    table = F.array(*[F.struct(F.lit(name).alias("name"), F.array(*map(F.lit, ids)).alias("ids")) for name, ids in RULES])
    flat = F.concat(F.lit(","), F.array_join("sequence", ",,"), F.lit(","))
    matched = F.filter(table, lambda r: F.like(flat, F.concat(F.lit("%"), F.array_join(F.transform(r["ids"], lambda s: F.concat(F.lit(","), s, F.lit(","))), "%"), F.lit("%"))))
    whole = by_doc.withColumn("matched", matched)
    contained = lambda r: F.exists("matched", lambda o: (F.size(o["ids"]) > F.size(r["ids"])) & (F.size(F.array_except(r["ids"], o["ids"])) == 0))
    licenses = F.array_sort(F.array_distinct(F.transform(F.filter("matched", lambda r: ~contained(r)), lambda r: r["name"])))
    return whole.select("id", "n_sentences", "sequence", licenses.alias("licenses"))


def op9_license_scan(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = scan(docs)
    return found.select(F.col("id").alias("doc_id"), "n_sentences", F.array_join("sequence", ",").alias("sentence_ids"), F.array_join("licenses", ",").alias("licenses"))


def _values(rows: list[tuple]) -> str:
    return ", ".join("(" + ", ".join(str(x) if isinstance(x, int) else "'" + x.replace("'", "''") + "'" for x in r) + ")" for r in rows)


OP9_SQL = f"""
WITH known(sid, norm) AS (VALUES {_values(list(SENTENCES.items()))}),
rules(rid, name, pattern, n) AS (VALUES {_values([(i, name, "%" + "%".join(f",{s}," for s in ids) + "%", len(ids)) for i, (name, ids) in enumerate(RULES)])}),
parts(rid, sid) AS (VALUES {_values([(i, s) for i, (_, ids) in enumerate(RULES) for s in ids])}),
cut AS (
  SELECT doc_id, regexp_split_to_array(regexp_replace(text, '[.!?:]+(\\s|$)', chr(10), 'g'), '[\\n\\r;]+') AS s FROM documents WHERE text IS NOT NULL),
norm AS (
  SELECT doc_id, i AS pos, trim(regexp_replace(lower(s[i]), '[^a-z0-9]+', ' ', 'g')) AS norm
  FROM (SELECT doc_id, s, unnest(range(1, len(s) + 1)) AS i FROM cut)),
hits AS (SELECT doc_id, pos, sid FROM norm JOIN known USING (norm)),
seq AS (SELECT doc_id, count(*) AS n_sentences, string_agg(sid, ',' ORDER BY pos) AS sentence_ids FROM hits GROUP BY doc_id),
matched AS (
  SELECT doc_id, rid, name, n FROM seq JOIN rules ON ',' || replace(sentence_ids, ',', ',,') || ',' LIKE pattern),
longest AS (
  SELECT m.doc_id, m.name FROM matched m WHERE NOT EXISTS (
    SELECT 1 FROM matched o WHERE o.doc_id = m.doc_id AND o.n > m.n AND NOT EXISTS (
      SELECT 1 FROM parts p WHERE p.rid = m.rid AND p.sid NOT IN (SELECT q.sid FROM parts q WHERE q.rid = o.rid)))),
names AS (SELECT doc_id, string_agg(name, ',' ORDER BY name) AS licenses FROM (SELECT DISTINCT doc_id, name FROM longest) GROUP BY doc_id)
SELECT doc_id, n_sentences, sentence_ids, coalesce(licenses, '') AS licenses FROM seq LEFT JOIN names USING (doc_id)
"""
