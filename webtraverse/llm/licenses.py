"""Licence scan: sparse TF-IDF cosine of headers and licence files to templates, and inheritance along directories. DataFrame functions only.

A template is a passage of a licence: a notice, a name, an SPDX line or a sentence of the full text. Wherever a whole text holds the rare
term that a template is anchored at, the words around it are lined up with the template, across line ends and whatever stands before and
after; this window is weighed by TF-IDF and compared by cosine. Document frequencies of the templates' terms are counted over all documents; a
term outside the templates weighs as one never seen. A place names the licence of its best template, if the cosine is at least
``threshold``; a document takes its best place. A document of which such windows cover ``file_share`` of the words, or whose file name
says so, is a licence file: it covers its directory and all below, and a document without a notice of its own inherits from the nearest directory above that has one.

Templates are literals: their terms, the frequencies of these and the weights are bounded by them and may be broadcast. Neither texts nor their words are
shuffled, only windows that can reach the threshold: those whose shared terms hold at least its square of the template's squared weight, which is exact by
Cauchy's inequality. What a text says is worked out once for each text, not for each row. Inheritance joins distinct directories, not
documents, with the directories that hold a licence file.

Behaviour at the edges: null text has no notice; ties go to the licence that sorts first, then to the earlier place; of several licence
files in a directory the one with the highest cosine counts, then the licence that sorts first; a null path counts as empty; rows
may repeat and ids may be null or shared, as every row is judged by its own text and path; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, text_column
from .url_filter import LOWER, UPPER

#: Public licence passages, each with the term that it is anchored at.
TEMPLATES = (
    ("agpl-3.0", "affero", "Licensed under the GNU Affero General Public License, version 3."),
    ("agpl-3.0", "affero", "GNU Affero General Public License"),
    ("agpl-3.0", "spdx", "SPDX-License-Identifier: AGPL-3.0"),
    ("apache-2.0", "apache", "Licensed under the Apache License, Version 2.0."),
    ("apache-2.0", "apache", "Apache License, Version 2.0"),
    ("apache-2.0", "spdx", "SPDX-License-Identifier: Apache-2.0"),
    ("bsd-3-clause", "redistribution", "Redistribution and use in source and binary forms, with or without modification, are permitted."),
    ("bsd-3-clause", "redistributions", "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."),
    ("bsd-3-clause", "redistributions", "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation"),
    ("bsd-3-clause", "endorse", "the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission"),
    ("bsd-3-clause", "spdx", "SPDX-License-Identifier: BSD-3-Clause"),
    ("cc-by-4.0", "cc", "Licensed under CC BY 4.0."),
    ("cc-by-4.0", "spdx", "SPDX-License-Identifier: CC-BY-4.0"),
    ("cc-by-nc-4.0", "cc", "Licensed under CC BY-NC 4.0."),
    ("cc-by-nc-4.0", "spdx", "SPDX-License-Identifier: CC-BY-NC-4.0"),
    ("cc-by-sa-4.0", "cc", "Licensed under CC BY-SA 4.0."),
    ("cc-by-sa-4.0", "spdx", "SPDX-License-Identifier: CC-BY-SA-4.0"),
    ("cc0-1.0", "cc0", "Dedicated to the public domain under CC0 1.0."),
    ("cc0-1.0", "spdx", "SPDX-License-Identifier: CC0-1.0"),
    ("gpl-2.0", "gnu", "This work is licensed under the GNU General Public License, version 2."),
    ("gpl-2.0", "gnu", "GNU General Public License, version 2"),
    ("gpl-2.0", "spdx", "SPDX-License-Identifier: GPL-2.0"),
    ("gpl-3.0", "gnu", "This work is licensed under the GNU General Public License, version 3."),
    ("gpl-3.0", "gnu", "GNU General Public License, version 3"),
    ("gpl-3.0", "spdx", "SPDX-License-Identifier: GPL-3.0"),
    ("isc", "hereby", "Permission to use, copy, modify, and distribute this software for any purpose with or without fee is hereby granted"),
    ("isc", "disclaims", "The software is provided as is and the author disclaims all warranties with regard to this software"),
    ("isc", "spdx", "SPDX-License-Identifier: ISC"),
    ("lgpl-3.0", "lesser", "This library is licensed under the GNU Lesser General Public License, version 3."),
    ("lgpl-3.0", "lesser", "GNU Lesser General Public License"),
    ("lgpl-3.0", "spdx", "SPDX-License-Identifier: LGPL-3.0"),
    ("mit", "license", "Released under the MIT License."),
    ("mit", "license", "MIT License"),
    ("mit", "hereby", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"),
    ("mit", "sublicense", "without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software"),
    ("mit", "portions", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software"),
    ("mit", "warranty", "The software is provided as is, without warranty of any kind, express or implied"),
    ("mit", "liable", "In no event shall the authors or copyright holders be liable for any claim, damages or other liability"),
    ("mit", "spdx", "SPDX-License-Identifier: MIT"),
    ("mpl-2.0", "mozilla", "Subject to the terms of the Mozilla Public License, version 2.0."),
    ("mpl-2.0", "mozilla", "Mozilla Public License, version 2.0"),
    ("mpl-2.0", "spdx", "SPDX-License-Identifier: MPL-2.0"),
    ("proprietary", "reserved", "All rights reserved."),
)
THRESHOLD, FILE_SHARE = 0.75, 0.5
FILE_NAMES = r"(?i)(^|/)(licen[cs]e|copying|notice)(\.[a-z]+)?$"


def _words(text: str) -> list[str]:
    return [t for t in re.split("[^a-z0-9]+", text.lower()) if t]


ANCHORS = sorted({a for _, a, _ in TEMPLATES})
ANCHOR_PATTERN = "(^|[^a-z0-9])(" + "|".join(ANCHORS) + ")([^a-z0-9]|$)"
#: How far a window extends before and behind its anchor, at most.
BEFORE = max(_words(t).index(a) for _, a, t in TEMPLATES)
BEHIND = max(len(_words(t)) - 1 - _words(t).index(a) for _, a, t in TEMPLATES)


def _lower(c):
    return F.translate(c, UPPER, LOWER)


def _terms(c):
    return F.filter(F.split(c, "[^a-z0-9]+"), lambda x: x != "")


def vocabulary() -> list[str]:
    return sorted({t for _, _, text in TEMPLATES for t in _words(text)})


def term_weights(texts: DataFrame) -> tuple[dict[str, float], float]:
    """IDF of each template term over all of ``texts`` (lower), and that of a term never seen; bounded by the templates."""
    words = vocabulary()
    found = F.array_intersect(F.split("lower", "[^a-z0-9]+"), F.array(*map(F.lit, words)))
    counted = texts.select(F.explode(F.concat(found, F.array(F.lit(""))))).groupBy("col").agg(F.count("*").alias("n")).collect()
    df = {r["col"]: r["n"] for r in counted}
    n = df.get("", 0)
    idf = lambda d: math.log((n + 1) / (d + 1)) + 1
    return {w: idf(df.get(w, 0)) for w in words}, idf(0)


def _templates(spark, idf: dict[str, float]) -> DataFrame:
    """template, license, anchor, before and length of its window, norm, and (term, weight) of its terms."""
    rows = []
    for i, (licence, anchor, text) in enumerate(TEMPLATES):
        words = _words(text)
        terms = sorted((w, words.count(w) * idf[w]) for w in set(words))
        rows.append((i, licence, anchor, words.index(anchor), len(words), math.sqrt(sum(w * w for _, w in terms)), terms))
    return spark.createDataFrame(rows, "template int, license string, anchor string, before int, length int, tnorm double, terms array<struct<term:string,tw:double>>")


def notices(texts: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(h1, h2, place, license, score, start, n) of each place that names a licence, once for each text; ``texts`` are (h1, h2, lower)."""
    spark = texts.sparkSession
    idf, unseen = term_weights(texts)
    weights = F.broadcast(spark.createDataFrame(list(idf.items()), "term string, idf double"))
    templates = _templates(spark, idf)
    tokens = texts.where(F.col("lower").rlike(ANCHOR_PATTERN)).select("h1", "h2", _terms("lower").alias("tokens"))
    places = F.filter(F.transform("tokens", lambda t, i: F.when(t.isin(*ANCHORS), i)), lambda i: i.isNotNull())
    from_ = lambda i: F.greatest(i - BEFORE, F.lit(0))
    near = F.transform(places, lambda i: F.struct(i.alias("place"), F.get("tokens", i).alias("anchor"), from_(i).alias("first"), F.slice("tokens", from_(i) + 1, F.lit(BEFORE + BEHIND + 1)).alias("near")))
    met = tokens.select("h1", "h2", F.size("tokens").alias("n_terms"), F.explode(near).alias("x")).select("h1", "h2", "n_terms", "x.*").join(F.broadcast(templates), "anchor")
    start = F.greatest(F.col("place") - F.col("before"), F.lit(0))
    window = F.slice("near", start - F.col("first") + 1, F.col("length") - F.greatest(F.col("before") - F.col("place"), F.lit(0)))
    met = met.withColumn("start", start).withColumn("window", window)
    shared = F.aggregate(F.filter("terms", lambda t: F.array_contains("window", t["term"])), F.lit(0.0), lambda s, t: s + t["tw"] * t["tw"])
    met = met.where(shared >= F.lit(threshold * threshold * (1 - 1e-9)) * F.col("tnorm") * F.col("tnorm"))
    met = met.groupBy("h1", "h2", "place", "template").agg(*(F.any_value(c).alias(c) for c in ("license", "start", "n_terms", "window")))
    # Equal windows are scored once.
    tf = met.select("template", "window").distinct().select("template", "window", F.explode("window").alias("term")).groupBy("template", "window", "term").agg(F.count("*").alias("tf"))
    weighed = tf.join(weights, "term", "left").withColumn("w", F.col("tf") * F.coalesce("idf", F.lit(unseen)))
    own = F.broadcast(templates.select("template", "tnorm", F.explode("terms").alias("t")).select("template", "tnorm", "t.term", "t.tw"))
    sums = weighed.join(own, ["template", "term"], "left").groupBy("template", "window").agg(F.sum(F.col("w") * F.col("tw")).alias("dot"), F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"), F.max("tnorm").alias("tnorm"))
    scored = sums.select("template", "window", F.round(F.col("dot") / (F.col("norm") * F.col("tnorm")), 6).alias("score")).where(F.col("score") >= threshold)
    best = met.join(scored, ["template", "window"]).groupBy("h1", "h2", "place").agg(F.min(F.struct((-F.col("score")).alias("s"), "license", "start", F.size("window").alias("n"))).alias("b"), F.any_value("n_terms").alias("n_terms"))
    return best.select("h1", "h2", "place", "b.license", (-F.col("b.s")).alias("score"), "b.start", "b.n", "n_terms")


def scan(files: DataFrame, threshold: float = THRESHOLD, file_share: float = FILE_SHARE) -> DataFrame:
    """For ``files`` (row_id, path, text): row_id, path, license, origin (own or inherited), score, n_notices."""
    text = text_column(files)
    hashes = (F.xxhash64(F.lit(1), text).alias("h1"), F.xxhash64(F.lit(2), text).alias("h2"))
    found = materialize(notices(files.select(*hashes, _lower(text).alias("lower")), threshold), "notices")  # small, and read three times
    covered = found.select("h1", "h2", F.explode(F.sequence("start", F.col("start") + F.col("n") - 1)).alias("at")).distinct().groupBy("h1", "h2").agg(F.count("*").alias("covered"))
    own = found.groupBy("h1", "h2").agg(F.min(F.struct((-F.col("score")).alias("s"), "license", "place")).alias("b"), F.count("*").alias("n_notices"), F.any_value("n_terms").alias("n_terms"))
    own = own.join(covered, ["h1", "h2"]).select("h1", "h2", F.col("b.license").alias("own"), (-F.col("b.s")).alias("score"), "n_notices", (F.col("covered") >= F.col("n_terms") * file_share).alias("whole"))
    rows = files.select("row_id", F.coalesce("path", F.lit("")).alias("path"), *hashes).withColumn("dir", F.regexp_extract("path", "^(.*)/[^/]*$", 1))
    judged = rows.join(own, ["h1", "h2"], "left")
    is_file = F.col("own").isNotNull() & (F.col("whole") | F.col("path").rlike(FILE_NAMES))
    holders = judged.where(is_file).groupBy("dir").agg(F.min(F.struct((-F.col("score")).alias("s"), "own")).alias("b")).select(F.col("dir").alias("above"), F.col("b.own").alias("given"))
    steps = F.split("dir", "/")
    above = F.transform(F.sequence(F.lit(1), F.size(steps)), lambda k: F.array_join(F.slice(steps, F.lit(1), k), "/"))
    dirs = rows.select("dir").distinct().select("dir", F.posexplode(above).alias("depth", "above"))
    inherited = dirs.join(holders, "above").groupBy("dir").agg(F.max_by("given", "depth").alias("given"))
    return judged.join(inherited, "dir", "left").select(
        "row_id", "path", F.coalesce("own", "given").alias("license"), F.when(F.col("own").isNotNull(), "own").when(F.col("given").isNotNull(), "inherited").alias("origin"), "score", F.coalesce("n_notices", F.lit(0)).cast("long").alias("n_notices")
    )


def scan_documents(docs: DataFrame) -> DataFrame:
    """The scan over ``documents``, whose directories are source, language and the thousand of the id."""
    path = F.concat_ws("/", F.coalesce("source", F.lit("")), F.coalesce("lang", F.lit("")), F.coalesce(F.expr("cast(doc_id div 1000 as string)"), F.lit("")), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))
    files = docs.select(F.col("doc_id").cast("long").alias("row_id"), path.alias("path"), "text")
    return scan(files).withColumnRenamed("row_id", "doc_id")


def oracle(threshold: float = THRESHOLD, file_share: float = FILE_SHARE) -> str:
    quoted = ", ".join("({}, '{}', '{}', '{}')".format(i, a, b, c.replace("'", "''")) for i, (a, b, c) in enumerate(TEMPLATES))
    split = "list_filter(regexp_split_to_array({}, '[^a-z0-9]+'), lambda x: x <> '')".format
    return f"""
with tpl as materialized (select template, license, anchor, {split('lower(passage)')} as words, list_position({split('lower(passage)')}, anchor) - 1 as before from (values {quoted}) v(template, license, anchor, passage)),
tt as materialized (select template, term, count(*) as tf from (select template, unnest(words) as term from tpl) group by all),
d as materialized (select row_number() over () as r, doc_id, concat_ws('/', coalesce(source, ''), coalesce(lang, ''), coalesce((doc_id // 1000)::varchar, ''), coalesce(doc_id::varchar, '')) as path, {split(f"translate(coalesce(text, ''), '{UPPER}', '{LOWER}')")} as tokens from documents),
n as (select count(*) as n from d),
df as (select term, count(*) as df from (select distinct r, unnest(tokens) as term from d) where term in (select term from tt) group by 1),
idf as materialized (select v.term, ln((n.n + 1) / (coalesce(df.df, 0) + 1)) + 1 as idf from (select distinct term from tt) v left join df using (term), n),
tw as materialized (select template, term, tf * idf as tw, sqrt(sum(tf * idf * tf * idf) over (partition by template)) as tnorm from tt join idf using (term)),
places as (select r, unnest(tokens) as anchor, unnest(range(len(tokens))) as place from d),
met as materialized (select p.r, p.place, t.template, t.license, greatest(p.place - t.before, 0) as start, d.tokens[greatest(p.place - t.before, 0) + 1 : p.place - t.before + len(t.words)] as w from places p join tpl t using (anchor) join d using (r)),
wt as (select r, place, template, term, count(*) as tf from (select r, place, template, unnest(w) as term from met) group by all),
ww as (select wt.*, tf * coalesce(idf, ln((n.n + 1) / 1) + 1) as x from wt left join idf using (term), n),
sums as (select r, place, ww.template, sum(x * tw) as dot, sqrt(sum(x * x)) as norm, max(tnorm) as tnorm from ww left join tw on tw.template = ww.template and tw.term = ww.term group by all),
best as materialized (select r, place, license, start, len(w) as n, round(dot / (norm * tnorm), 6) as score from sums join met using (r, place, template) where round(dot / (norm * tnorm), 6) >= {threshold} qualify row_number() over (partition by r, place order by score desc, license, start, n) = 1),
covered as (select r, count(*) as covered from (select distinct r, unnest(range(start, start + n)) as at from best) group by 1),
own as (select r, license as own, score, count(*) over (partition by r) as n_notices from best qualify row_number() over (partition by r order by score desc, license, place) = 1),
judged as materialized (select d.r, d.doc_id, d.path, regexp_extract(d.path, '^(.*)/[^/]*$', 1) as dir, o.own, o.score, o.n_notices, c.covered >= len(d.tokens) * {file_share} as whole from d left join own o using (r) left join covered c using (r)),
holders as (select dir as above, own as given from judged where own is not null and (whole or regexp_matches(path, '{FILE_NAMES}')) qualify row_number() over (partition by dir order by score desc, own) = 1),
up as (select dir, unnest(range(1, len(string_split(dir, '/')) + 1)) as depth from (select distinct dir from judged)),
inherited as (select dir, arg_max(given, depth) as given from up join holders on holders.above = array_to_string(string_split(dir, '/')[1:depth], '/') group by 1)
select doc_id, path, coalesce(own, given) as license, case when own is not null then 'own' when given is not null then 'inherited' end as origin, score, coalesce(n_notices, 0)::bigint as n_notices
from judged left join inherited using (dir)
"""
