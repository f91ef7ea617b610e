"""License scans by TF-IDF cosine to templates, then inheritance from the nearest ancestor directory; native only.

What is compared with the templates: lines that mention a license, blocks of several lines (between blank ones) that
do, and whole candidate files: texts that are named like licence files, or a quarter of whose words stand in such
blocks.  Parts with most of their distinct words outside the templates are left out at once: such words are rarer than
those of templates, so their cosine could not exceed the root of a half.  Equal parts are compared once.  Each becomes a sparse TF-IDF vector (document frequencies over all of them and
the templates) and has the template of the highest cosine among those whose threshold it reaches.  A document is
licensed by the best of its parts.  It is the licence file of its directory if at least half of its words stand in
parts with a license, if it opens with a license's title, or if it is named so.  Other documents take the license of
the nearest ancestor directory that has one, found by joining their ancestor paths.

Defined results: null text counts as empty, a null path part as ''; ties between templates go to the first name, and
between licence files of one directory to the larger share, then the smaller id; repeated rows get equal results;
an empty table gives none.  Input columns other than those named are ignored.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from momenttree.llm.runtime import cut

_WARRANTY = 'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.'
_MIT = 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:'
_MIT_NOTICE = "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."
_BSD = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"
_BSD_TWO = "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."
_BSD_THREE = "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."
_BSD_END = 'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.'
_ISC = "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."
_ISC_END = 'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.'
_APACHE = 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0'
_APACHE_END = 'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'
_APACHE_TERMS = '"License" shall mean the terms and conditions for use, reproduction, and distribution as defined by Sections 1 through 9 of this document. "Licensor" shall mean the copyright owner or entity authorized by the copyright owner that is granting the License.'
_GNU = "This program is free software: you can redistribute it and/or modify it under the terms of the GNU {} as published by the Free Software Foundation, either version {} of the License, or (at your option) any later version."
_GNU_END = "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU {0} for more details. You should have received a copy of the GNU {0} along with this program. If not, see http://www.gnu.org/licenses/."
_GNU_KINDS = [("AGPL-3.0", "Affero General Public License", "3", "19 November 2007"), ("GPL-2.0", "General Public License", "2", "June 1991"), ("GPL-3.0", "General Public License", "3", "29 June 2007"), ("LGPL-2.1", "Lesser General Public License", "2.1", "February 1999"), ("LGPL-3.0", "Lesser General Public License", "3", "29 June 2007")]
_CREATIVE = [("CC-BY-4.0", "Attribution 4.0", "CC BY 4.0"), ("CC-BY-SA-4.0", "Attribution-ShareAlike 4.0", "CC BY-SA 4.0"), ("CC-BY-NC-4.0", "Attribution-NonCommercial 4.0", "CC BY-NC 4.0"), ("CC-BY-ND-4.0", "Attribution-NoDerivatives 4.0", "CC BY-ND 4.0"), ("CC-BY-NC-SA-4.0", "Attribution-NonCommercial-ShareAlike 4.0", "CC BY-NC-SA 4.0"), ("CC-BY-NC-ND-4.0", "Attribution-NonCommercial-NoDerivatives 4.0", "CC BY-NC-ND 4.0")]
_SHORT_NAMES = ["0BSD", "AFL-3.0", "AGPL-3.0", "Apache-1.1", "Apache-2.0", "Artistic-2.0", "BSD-2-Clause", "BSD-3-Clause", "BSL-1.0", "CC-BY-4.0", "CC-BY-NC-4.0", "CC-BY-NC-ND-4.0", "CC-BY-NC-SA-4.0", "CC-BY-ND-4.0", "CC-BY-SA-4.0", "CC0-1.0", "CDDL-1.0", "EPL-1.0", "EPL-2.0", "EUPL-1.2", "GPL-2.0", "GPL-3.0", "ISC", "LGPL-2.1", "LGPL-3.0", "MIT", "MIT-0", "MPL-1.1", "MPL-2.0", "MS-PL", "NCSA", "OFL-1.1", "OSL-3.0", "PostgreSQL", "Python-2.0", "Ruby", "Unlicense", "WTFPL", "X11", "Zlib"]
#: License id, form (title, notice, header, body, file or spdx), text.
TEMPLATES = [
    ("Apache-2.0", "title", "Apache License Version 2.0, January 2004 http://www.apache.org/licenses/"),
    ("Apache-2.0", "notice", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "header", _APACHE),
    ("Apache-2.0", "header", f"{_APACHE} {_APACHE_END}"),
    ("Apache-2.0", "body", _APACHE_TERMS),
    ("BSD-2-Clause", "title", "BSD 2-Clause License"),
    ("BSD-2-Clause", "body", f"{_BSD} {_BSD_TWO}"),
    ("BSD-2-Clause", "file", f"BSD 2-Clause License Copyright (c) All rights reserved. {_BSD} {_BSD_TWO} {_BSD_END}"),
    ("BSD-3-Clause", "title", "BSD 3-Clause License"),
    ("BSD-3-Clause", "notice", "Redistribution and use in source and binary forms, with or without modification, are permitted under the BSD 3-Clause License."),
    ("BSD-3-Clause", "body", f"{_BSD} {_BSD_TWO} {_BSD_THREE}"),
    ("BSD-3-Clause", "body", _BSD_THREE),
    ("BSD-3-Clause", "file", f"BSD 3-Clause License Copyright (c) All rights reserved. {_BSD} {_BSD_TWO} {_BSD_THREE} {_BSD_END}"),
    ("BSL-1.0", "title", "Boost Software License - Version 1.0 - August 17th, 2003"),
    ("BSL-1.0", "header", "Distributed under the Boost Software License, Version 1.0. (See accompanying file LICENSE_1_0.txt or copy at http://www.boost.org/LICENSE_1_0.txt)"),
    ("CC0-1.0", "title", "CC0 1.0 Universal"),
    ("CC0-1.0", "notice", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work under CC0 1.0 Universal."),
    ("EPL-2.0", "title", "Eclipse Public License - v 2.0"),
    ("EPL-2.0", "header", "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at https://www.eclipse.org/legal/epl-2.0/"),
    ("ISC", "title", "ISC License"),
    ("ISC", "body", _ISC),
    ("ISC", "file", f"ISC License Copyright (c) {_ISC} {_ISC_END}"),
    ("MIT", "title", "The MIT License (MIT)"),
    ("MIT", "title", "MIT License"),
    ("MIT", "notice", "Released under the MIT License."),
    ("MIT", "notice", "This project is licensed under the terms of the MIT license."),
    ("MIT", "body", _MIT),
    ("MIT", "body", _MIT_NOTICE),
    ("MIT", "file", f"MIT License Copyright (c) {_MIT} {_MIT_NOTICE} {_WARRANTY}"),
    ("MPL-2.0", "title", "Mozilla Public License Version 2.0"),
    ("MPL-2.0", "notice", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("MPL-2.0", "header", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("Unlicense", "title", "The Unlicense"),
    ("Unlicense", "body", "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."),
    ("Zlib", "title", "zlib License"),
    ("Zlib", "body", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:"),
    *((i, "title", f"GNU {n} Version {v}") for i, n, v, _ in _GNU_KINDS),
    *((i, "title", f"GNU {n} Version {v}, {day}") for i, n, v, day in _GNU_KINDS),
    *((i, "notice", f"{what} is licensed under the GNU {n}, version {v}.") for i, n, v, _ in _GNU_KINDS for what in ("This work", "This library")),
    *((i, "header", _GNU.format(n, v)) for i, n, v, _ in _GNU_KINDS),
    *((i, "header", f"{_GNU.format(n, v)} {_GNU_END.format(n)}") for i, n, v, _ in _GNU_KINDS),
    *((i, "title", f"Creative Commons {n} International Public License") for i, n, _ in _CREATIVE),
    *((i, "notice", f"This work is licensed under a Creative Commons {n} International License, {short}.") for i, n, short in _CREATIVE),
    *((i, "notice", f"Licensed under {short}.") for i, _, short in _CREATIVE),
    *((i, "spdx", f"SPDX-License-Identifier: {i}{end}") for i in _SHORT_NAMES for end in (("", "-only", "-or-later") if "GPL" in i else ("",))),
]
MENTION = r"(?i)licen[sc]e|copyright|spdx-|permission is hereby|redistribution|free software|public domain"
FILE_NAME = r"(?i)(^|/)(licen[sc]e|copying|notice)(\.[a-z]+)?$"
#: What separates blocks: lines that are empty but for comment marks.
BLANK = r"\n(?:[ \t\r*#/;%<>!-]*\n)+"
WORD = r"[0-9]+(?:\.[0-9]+)*|[a-z]+"
#: The distinct words of all templates.
VOCABULARY = sorted({w for _, _, t in TEMPLATES for w in re.findall(WORD, t.lower())})
LEAST = 0.7
#: Titles and identifiers are short, and differ from one another in single terms.
LEAST_SHORT = {"title": 0.85, "spdx": 0.95}
FILE_SHARE = 0.5
CANDIDATE_SHARE = 0.25


def _words(text: Column) -> Column:
    """Runs of letters, numbers with their inner dots."""
    return F.regexp_extract_all(F.lower(text), F.lit(WORD), F.lit(0))


def default_path() -> Column:
    """Of documents: source / language / hundred of ids / id."""
    part = lambda c: F.coalesce(F.col(c).cast("string"), F.lit(""))
    return F.concat_ws("/", part("source"), part("lang"), F.coalesce(F.floor(F.col("doc_id") / 100).cast("string"), F.lit("")), part("doc_id"))


def _templates(spark: SparkSession) -> DataFrame:
    """template (its number), license, form, least, text as literals of the plan."""
    one = lambda k, t: F.struct(F.lit(k).alias("template"), F.lit(t[0]).alias("license"), F.lit(t[1]).alias("form"), F.lit(LEAST_SHORT.get(t[1], LEAST)).alias("least"), F.lit(t[2]).alias("text"))
    return spark.range(1).select(F.explode(F.array(*(one(k, t) for k, t in enumerate(TEMPLATES)))).alias("t")).select("t.*")


def classify(parts: DataFrame) -> DataFrame:
    """key, license, form, cosine of the distinct parts (key, text) that reach a template's threshold."""
    templates = _templates(parts.sparkSession)
    counted = lambda df, key: df.select(key, F.explode(_words(F.col("text"))).alias("term")).groupBy(key, "term").agg(F.count("*").alias("tf"))
    terms = cut(counted(parts, "key"))
    model = counted(templates, "template")
    n = parts.select("key").distinct().count() + len(TEMPLATES)
    rarity = terms.select("term").union(model.select("term")).groupBy("term").agg((F.log(F.lit(n + 1.0) / (F.count("*") + 1)) + 1).alias("idf"))
    rarity = cut(rarity)
    weigh = lambda df, key: df.join(rarity, "term").select(key, "term", (F.col("tf") * F.col("idf")).alias("w"))
    weighted = cut(weigh(terms, "key"))
    norms = weighted.groupBy("key").agg(F.sqrt(F.sum(F.col("w") ** 2)).alias("norm"))
    model = weigh(model, "template")  # a fixed list of texts: bounded, so it may be broadcast
    sizes = model.groupBy("template").agg(F.sqrt(F.sum(F.col("w") ** 2)).alias("size"))
    units = F.broadcast(cut(model.join(sizes, "template").select("template", "term", (F.col("w") / F.col("size")).alias("unit"))))
    dots = weighted.join(units, "term").groupBy("key", "template").agg(F.sum(F.col("w") * F.col("unit")).alias("dot"))
    scored = dots.join(norms, "key").join(F.broadcast(templates.drop("text")), "template").withColumn("cosine", F.round(F.col("dot") / F.col("norm"), 9)).where("cosine >= least")
    best = scored.groupBy("key").agg(F.min(F.struct((-F.col("cosine")).alias("order"), "license", "form")).alias("best"))
    return best.select("key", "best.license", "best.form", (-F.col("best.order")).alias("cosine"))


def scan(docs: DataFrame, path: Column | None = None) -> DataFrame:
    """doc_id, path, license, cosine, found (header, file, inherited or none), inherited_from."""
    where = default_path() if path is None else path
    text = F.regexp_replace(F.coalesce(F.col("text").cast("string"), F.lit("")), r"^\s+", "")
    mentions = lambda x: x.rlike(MENTION)
    part = lambda level, first: lambda x, k: F.struct(F.lit(level).alias("level"), (first & (k == 0)).alias("first"), x.alias("text"))
    lines = F.filter(F.transform(F.split(F.col("text"), r"[\r\n]+"), part("line", F.lit(True))), lambda x: mentions(x["text"]))
    all_blocks = F.filter(F.transform(F.split(F.col("text"), BLANK), part("block", F.lit(True))), lambda x: mentions(x["text"]))
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), where.alias("path"), text.alias("text"))
    rows = rows.withColumn("hinted", mentions(F.col("text"))).withColumn("blocks", F.when(F.col("hinted"), all_blocks)).withColumn("n_words", F.when(F.col("hinted"), F.size(_words(F.col("text")))))
    inside = F.aggregate("blocks", F.lit(0), lambda n, x: n + F.size(_words(x["text"])))
    is_candidate = F.coalesce(F.col("path").rlike(FILE_NAME), F.lit(False)) | (inside >= CANDIDATE_SHARE * F.col("n_words"))
    whole = F.when(is_candidate, F.array(F.struct(F.lit("text").alias("level"), F.lit(False).alias("first"), F.col("text").alias("text")))).otherwise(F.array())
    several = F.filter("blocks", lambda x: x["text"].contains("\n"))
    known = F.array(*map(F.lit, VOCABULARY))

    def familiar(x: Column) -> Column:
        words = F.array_distinct(_words(x["text"]))
        return 2 * F.size(F.array_intersect(words, known)) >= F.size(words)

    parts = F.when(F.col("hinted"), F.filter(F.concat(lines, several, whole), familiar)).alias("parts")
    rows = cut(rows.select(F.monotonically_increasing_id().alias("row"), "doc_id", "path", "n_words", parts))
    each = rows.select("row", "doc_id", "path", "n_words", F.explode("parts").alias("p")).select("row", "doc_id", "path", "n_words", "p.*")
    each = cut(each.withColumn("key", F.substring(F.sha2(F.col("text").cast("binary"), 256), 1, 32)).withColumn("size", F.size(_words(F.col("text")))))
    known = classify(cut(each.groupBy("key").agg(F.first("text").alias("text"))))
    level = lambda name: F.coalesce(F.sum(F.when(F.col("level") == name, F.col("size"))), F.lit(0))
    share = (F.greatest(*map(level, ("line", "block", "text"))) / F.max("n_words")).alias("share")
    own = each.drop("text").join(known, "key").groupBy("row", "doc_id", "path").agg(F.min(F.struct((-F.col("cosine")).alias("order"), "license")).alias("best"), share, F.max(F.col("first") & (F.col("form") == "title")).alias("titled"))
    is_file = (F.col("share") >= FILE_SHARE) | F.col("titled") | F.coalesce(F.col("path").rlike(FILE_NAME), F.lit(False))
    licensed = cut(own.select("row", "doc_id", "path", "best.license", (-F.col("best.order")).alias("cosine"), "share", is_file.alias("is_file")))
    files = licensed.where("is_file").withColumn("folder", F.regexp_extract("path", r"^(.*)/[^/]*$", 1))
    by_folder = files.groupBy("folder").agg(F.min(F.struct((-F.col("share")).alias("order"), "doc_id", "license")).alias("best")).select("folder", F.col("best.license").alias("given"))

    others = rows.select("row", "doc_id", "path").join(licensed.select("row"), "row", "left_anti")
    steps = F.split("path", "/")
    depths = F.expr("sequence(0, size(split(path, '/')) - 1)")
    ancestors = others.select("row", F.explode(F.transform(depths, lambda d: F.struct(d.alias("depth"), F.array_join(F.slice(steps, F.lit(1), d), "/").alias("folder")))).alias("a")).select("row", "a.depth", "a.folder")
    nearest = ancestors.join(by_folder, "folder").groupBy("row").agg(F.max(F.struct("depth", "given", "folder")).alias("n")).select("row", "n.given", F.col("n.folder").alias("inherited_from"))
    inherited = others.join(nearest, "row", "left").select("doc_id", "path", F.col("given").alias("license"), F.lit(None).cast("double").alias("cosine"), F.when(F.col("given").isNotNull(), "inherited").otherwise("none").alias("found"), "inherited_from")
    return licensed.select("doc_id", "path", "license", "cosine", F.when(F.col("is_file"), "file").otherwise("header").alias("found"), F.lit(None).cast("string").alias("inherited_from")).union(inherited)
