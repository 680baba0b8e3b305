"""License notices in texts: an exact set-similarity join with DataFrame functions only.

Text blocks (overlapping windows of words) join a small table of templates. Tokens are
ordered from the rarest in the corpus on; a block can only hold enough of a template if one
of the template's first tokens is among the block's first ones (prefix filter), if the block
has enough tokens at all (length filter), and if enough tokens are left behind the shared
one on both sides (positional filter). What passes is counted exactly. Windows are as wide as
the templates need: templates fall into classes by length, and any run of words as long as
a template lies in one block of its class.

Every text is normalised once: what is written is a digest, the template tokens it has, and the
words of texts that have enough of some template or hold a phrase; all else reads that.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubelens.storage import keep, materialize

THRESHOLD = 0.8
#: Distance of the blocks of the shortest templates; a block holds two strides, so any run of a stride and a word lies in one.
STRIDE = 32

#: Phrases and labels of the base contract.
BASE_PHRASES = (("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc"))

#: Notices (public texts) and their labels.
NOTICES = (
    ("released under the mit license", "mit"),
    ("permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "mit"),
    ("licensed under the apache license version 2 0", "apache-2"),
    ("you may not use this file except in compliance with the license you may obtain a copy of the license at www apache org licenses license 2 0", "apache-2"),
    ("licensed under cc by nc 4 0", "cc-by-nc"),
    ("creative commons attribution noncommercial 4 0 international license", "cc-by-nc"),
    ("creative commons attribution sharealike 4 0 international license", "cc-by-sa"),
    ("this work is licensed under the gnu general public license version 3", "gpl-3"),
    ("under the terms of the gnu affero general public license", "agpl"),
    ("under the terms of the gnu lesser general public license", "lgpl"),
    ("redistribution and use in source and binary forms with or without modification are permitted", "bsd"),
    ("subject to the terms of the mozilla public license v 2 0", "mpl-2"),
    ("this is free and unencumbered software released into the public domain", "public-domain"),
    ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "isc"),
)


#: Whole license texts and file headers (public texts) and their labels.
LICENSE_TEXTS = (
    (
        """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation
        files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy,
        modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software
        is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be
        included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND,
        EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND
        NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY,
        WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR
        OTHER DEALINGS IN THE SOFTWARE.""",
        "mit",
    ),
    (
        """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following
        conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the
        following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and
        the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED
        BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE
        IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT
        HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING,
        BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION)
        HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR
        OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.""",
        "bsd",
    ),
    (
        """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted,
        provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND
        THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND
        FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES
        WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION,
        ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
        "isc",
    ),
    (
        """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the
        License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law
        or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR
        CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and
        limitations under the License.""",
        "apache-2",
    ),
    (
        """This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License
        as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This
        program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of
        MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have
        received a copy of the GNU General Public License along with this program.""",
        "gpl-3",
    ),
    (
        """This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not
        distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.""",
        "mpl-2",
    ),
    (
        """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for
        any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose,
        including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: The
        origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this
        software in a product, an acknowledgment in the product documentation would be appreciated but is not required. Altered
        source versions must be plainly marked as such, and must not be misrepresented as being the original software. This notice
        may not be removed or altered from any source distribution.""",
        "zlib",
    ),
)
TEMPLATES = (*NOTICES, *LICENSE_TEXTS)


@dataclass(frozen=True)
class Template:
    """A notice: its distinct tokens, how many of them a block needs, and the stride of the blocks it is looked for in."""

    number: int
    label: str
    tokens: tuple[str, ...]
    needed: int
    stride: int


def templates(threshold: float = THRESHOLD, texts=TEMPLATES) -> list[Template]:
    """A template of any length: its stride is the smallest power of two, from STRIDE on, that its words exceed by one at most."""
    out = []
    for k, (text, label) in enumerate(texts):
        words = re.findall(r"[0-9a-z\u0080-\U0010ffff]+", text.translate(_LOWER))
        tokens, stride = tuple(dict.fromkeys(words)), STRIDE
        while stride + 1 < len(words):
            stride *= 2
        if tokens:
            out.append(Template(k, label, tokens, math.ceil(threshold * len(tokens) - 1e-9), stride))
    return out


_LOWER = {c: c + 32 for c in range(65, 91)}


def normal_words(text: Column) -> Column:
    """The words of a text joined by single spaces: A-Z lowered, then runs of 0-9, a-z and non-ASCII."""
    low = F.translate(F.coalesce(text, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.trim(F.regexp_replace(low, r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", " "))


def _all(columns: list[Column]) -> Column:
    out = columns[0]
    for c in columns[1:]:
        out = out & c
    return out


def phrase_starts(words: Column, norm: Column, phrase: str) -> Column:
    """Sorted word numbers at which the phrase's words stand; the array is empty without a scan if its text is absent."""
    parts = phrase.split()
    at = F.filter(F.sequence(F.lit(0), F.greatest(F.size(words) - 1, F.lit(0))), lambda i: F.coalesce(_all([F.get(words, i + k) == p for k, p in enumerate(parts)]), F.lit(False)))
    return F.when(norm.contains(phrase), at).otherwise(F.array().cast("array<int>"))


def normalised(docs: DataFrame, items: list[Template]) -> DataFrame:
    """(doc_id, key, n_words, have, norm), one row per row of ``docs``: the only pass over the texts.

    ``have`` are the template tokens of the text. ``norm`` is null unless the text has enough of
    some template's tokens, or holds a phrase: no block can have more than its text.
    """
    known = F.array(*[F.lit(t) for t in sorted({t for x in items for t in x.tokens})])
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), normal_words(F.col("text")).alias("norm"))
    n_words = F.when(F.col("norm") == "", 0).otherwise(F.length("norm") - F.length(F.replace(F.col("norm"), F.lit(" "))) + 1)
    key = F.struct(F.xxhash64("norm").alias("h"), F.length("norm").alias("n"), F.crc32("norm").alias("c"))
    base = base.select("doc_id", key.alias("key"), n_words.cast("long").alias("n_words"), F.array_intersect(known, F.split("norm", " ")).alias("have"), "norm")
    wanted = F.array(*[F.struct(F.array(*map(F.lit, x.tokens)).alias("t"), F.lit(x.needed).alias("n")) for x in items])
    enough = (F.size("have") >= min(x.needed for x in items)) & F.exists(wanted, lambda x: F.size(F.array_intersect(F.col("have"), x["t"])) >= x["n"])
    holds = F.col("norm").rlike("|".join(p for p, _ in BASE_PHRASES))
    return base.withColumn("norm", F.when(enough | holds, F.col("norm")))


def token_order(have: DataFrame, items: list[Template]) -> list[str]:
    """Template tokens from the rarest on, by the number of texts (column have) that have them, then by token.

    One row a token reaches the driver; the tokens are those of the templates.
    """
    counts = {r.token: r["count"] for r in have.select(F.explode("have").alias("token")).groupBy("token").count().collect()}
    return sorted({t for x in items for t in x.tokens}, key=lambda t: (counts.get(t, 0), t))


def find_notices(texts: DataFrame, items: list[Template]) -> DataFrame:
    """(key, notices): for the rows of ``normalised`` texts with a notice, an array of (label, containment, block), by block, then label.

    ``key`` identifies a row or equal rows. Every block of every text that holds enough of a
    template's distinct tokens is found; ``block`` is the number of its first word.
    """
    order = token_order(texts, items)
    rank = {t: i for i, t in enumerate(order)}
    ordered = {x.number: sorted(x.tokens, key=rank.get) for x in items}
    index = texts.sparkSession.createDataFrame(
        [(x.stride, t, p, len(x.tokens), x.needed, x.label, ordered[x.number]) for x in items for p, t in enumerate(ordered[x.number][: len(x.tokens) - x.needed + 1])],
        "stride int, token string, place int, size int, needed int, label string, tokens array<string>",
    )
    known = F.array(*map(F.lit, order))
    strides = sorted({x.stride for x in items})
    least = F.element_at(F.create_map(*[F.lit(v) for s in strides for v in (s, min(x.needed for x in items if x.stride == s))]), F.col("stride"))
    rows = texts.filter("norm is not null and n_words > 0").select("key", F.split("norm", " ").alias("words"))

    def starts(stride: int) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size("words") - 1, F.lit(stride)), lambda at: F.struct(F.lit(stride).alias("stride"), at.alias("block")))

    blocks = rows.select("key", "words", F.explode(F.concat(*map(starts, strides))).alias("b")).select("key", "words", "b.*")
    # array_intersect keeps the order of its first argument: tokens from the rarest on
    have = F.array_intersect(known, F.slice("words", F.col("block") + 1, F.col("stride") * 2))
    blocks = blocks.select("key", "stride", "block", have.alias("have"), least.alias("least")).filter("size(have) >= least")
    shared = blocks.select("key", "stride", "block", "have", F.posexplode(F.slice("have", F.lit(1), F.size("have") - F.col("least") + 1)).alias("at", "token"))
    pairs = shared.join(F.broadcast(index), ["stride", "token"])  # templates times their prefixes
    left = F.least(F.col("size") - F.col("place"), F.size("have") - F.col("at"))
    pairs = pairs.filter((F.size("have") >= F.col("needed")) & (F.col("at") <= F.size("have") - F.col("needed")) & (left >= F.col("needed")))
    overlap = F.size(F.array_intersect("have", "tokens"))
    hits = pairs.select("key", "block", "label", "needed", (overlap / F.col("size")).alias("containment"), overlap.alias("overlap")).filter("overlap >= needed")
    best = hits.groupBy("key", "label").agg(F.max("containment").alias("containment"), F.min("block").alias("block"))
    return best.groupBy("key").agg(F.array_sort(F.collect_list(F.struct("block", "label", "containment"))).alias("notices"))


def license_report(docs: DataFrame, threshold: float = THRESHOLD, texts=TEMPLATES) -> DataFrame:
    """(doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, notices), one row per row of ``docs``.

    A null or wordless text has no words, no labels and score 0; score is the best
    containment of a template that reaches the threshold, or 1 where a base phrase stands.
    Repeated rows and null doc_ids are kept; other columns are not read. ``release`` of the
    result deletes the table behind it.
    """
    items = templates(threshold, texts)
    read = materialize(normalised(docs, items), "norms")
    held = read.filter("norm is not null")
    # texts that hold a phrase are few: only they are cut into words, and equal ones count once
    marked = held.filter(F.col("norm").rlike("|".join(p for p, _ in BASE_PHRASES))).select("key", "norm", F.split("norm", " ").alias("words"))
    marked = marked.select(F.col("key").alias("m"), *[phrase_starts(F.col("words"), F.col("norm"), p).alias(f"s{k}") for k, (p, _) in enumerate(BASE_PHRASES)])
    marked = marked.groupBy("m").agg(*[F.first(f"s{k}").alias(f"s{k}") for k in range(len(BASE_PHRASES))])
    found = find_notices(read, items).withColumnRenamed("key", "k")
    out = held.select("doc_id", "key", "n_words").join(found, F.col("key") == F.col("k"), "left").join(marked, F.col("key") == F.col("m"), "left")
    none = F.array().cast("array<int>")
    starts = [F.coalesce(f"s{k}", none) for k in range(len(BASE_PHRASES))]
    every = F.concat(*starts)
    own = F.filter(F.array(*[F.when(F.size(starts[k]) > 0, F.lit(label)) for k, (_, label) in enumerate(BASE_PHRASES)]), lambda x: x.isNotNull())
    notices = F.coalesce("notices", F.array().cast("array<struct<block:int,label:string,containment:double>>"))
    report = out.select(
        "doc_id",
        "n_words",
        F.size(every).cast("long").alias("n_base"),
        F.array_min(every).cast("long").alias("first_word"),
        F.array_max(every).cast("long").alias("last_word"),
        F.concat_ws(",", F.array_sort(F.array_distinct(own))).alias("base_labels"),
        F.concat_ws(",", F.array_sort(F.array_distinct(F.concat(own, F.transform(notices, lambda x: x["label"]))))).alias("labels"),
        F.greatest(F.when(F.size(every) > 0, 1.0).otherwise(0.0), F.coalesce(F.array_max(F.transform(notices, lambda x: x["containment"])), F.lit(0.0))).alias("score"),
        F.to_json(notices).alias("notices"),
    )
    absent = F.lit(None).cast("long")
    empty = read.filter("norm is null").select("doc_id", "n_words", F.lit(0).cast("long").alias("n_base"), absent.alias("first_word"), absent.alias("last_word"), F.lit("").alias("base_labels"), F.lit("").alias("labels"), F.lit(0.0).alias("score"), F.lit("[]").alias("notices"))
    return keep(report.unionByName(empty), read)


def report_sql(threshold: float = THRESHOLD, texts=TEMPLATES) -> str:
    """DuckDB SQL for the contract's columns, by comparing every block with every template."""
    items = templates(threshold, texts)
    table = ", ".join(f"([{', '.join(repr(t) for t in x.tokens)}], {len(x.tokens)}, {x.needed}, '{x.label}', {x.stride})" for x in items)
    strides = ", ".join(f"({k})" for k in sorted({x.stride for x in items}))
    spots = " || ".join(f"list_filter(range(len(w)), lambda i: {' and '.join(f'w[i + {k + 1}] = {p!r}' for k, p in enumerate(phrase.split()))})" for phrase, _ in BASE_PHRASES)
    own = ", ".join(f"CASE WHEN contains(' ' || norm || ' ', ' {phrase} ') THEN '{label}' END" for phrase, label in BASE_PHRASES)
    return f"""
WITH t(tokens, size, needed, label, stride) AS (VALUES {table}), st(stride) AS (VALUES {strides}),
d AS (SELECT doc_id, trim(regexp_replace(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+', ' ', 'g')) AS norm FROM documents),
e AS (SELECT doc_id, norm, CASE WHEN norm = '' THEN []::VARCHAR[] ELSE string_split(norm, ' ') END AS w FROM d),
k AS (SELECT doc_id, norm, w FROM e WHERE len(list_intersect(w, (SELECT flatten(list(tokens)) FROM t))) > 0),
b AS (SELECT doc_id, stride, list_distinct(w[s + 1 : s + 2 * stride]) AS have FROM (SELECT doc_id, w, stride, unnest(range(0, len(w), stride)) AS s FROM k, st)),
h AS (SELECT doc_id, label, len(list_intersect(have, tokens)) / size AS c FROM b JOIN t USING (stride) WHERE len(list_intersect(have, tokens)) >= needed),
g AS (SELECT doc_id, list(DISTINCT label) AS labels, max(c) AS c FROM h GROUP BY doc_id),
f AS (SELECT doc_id, norm, len(w) AS n_words, {spots} AS spots, list_filter([{own}], lambda x: x IS NOT NULL) AS own FROM e)
SELECT f.doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(len(spots) AS BIGINT) AS n_base,
  CAST(list_min(spots) AS BIGINT) AS first_word, CAST(list_max(spots) AS BIGINT) AS last_word,
  array_to_string(list_sort(own), ',') AS base_labels,
  array_to_string(list_sort(list_distinct(own || coalesce(g.labels, []::VARCHAR[]))), ',') AS labels,
  CAST(greatest(CASE WHEN len(spots) > 0 THEN 1.0 ELSE 0.0 END, coalesce(g.c, 0.0)) AS DOUBLE) AS score
FROM f LEFT JOIN g USING (doc_id)
"""
