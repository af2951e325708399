"""Licence scans: sparse TF-IDF cosine to templates, then inheritance from the nearest ancestor directory (native).

Templates are whole licence texts, the standard file headers, and one-line notices. A text's passages are the whole of
it, its header, its paragraphs, lines, windows of two and three lines, and sentences, as far as they name licensing at all (a term
that begins with one of ``KEYWORDS``; every template does). Each is a sparse vector of term counts times inverse
document frequencies, and is held against every template by cosine. A file's own licence is that of its best passage.
A file that is a licence text as a whole, or has a licence file's name, speaks for its directory; files without a
licence of their own inherit from the nearest directory above, by an equi-join of paths.
"""

from __future__ import annotations

import math
import re
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, quoted

# Licence texts, file headers and notices as publicly used.
_AS_IS = """THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY,
WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
_MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of
the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"""
_BSD = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:
1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.
2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or
other materials provided with the distribution."""
_BSD_NAMES = """3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software
without specific prior written permission."""
_BSD_AS_IS = """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE
IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR
ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS
OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING
NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
_GNU = """This program is free software: you can redistribute it and/or modify it under the terms of the GNU {name} Public License as published by the Free Software
Foundation, either version {n} of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT
ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU {name} Public License for more details. You
should have received a copy of the GNU {name} Public License along with this program. If not, see https://www.gnu.org/licenses/."""
TEMPLATES = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("MIT", "Released under the MIT License."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("LGPL-3.0", "This library is licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "This program is licensed under the GNU Affero General Public License, version 3."),
    ("BSD-3-Clause", "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC0-1.0", "Dedicated to the public domain under the CC0 1.0 Universal dedication."),
    ("ARR", "All rights reserved."),
    ("MIT", _MIT),
    ("MIT", f"""MIT License. Copyright (c) {_MIT} The above copyright notice and this permission notice shall be included in all copies or substantial portions of
the Software. {_AS_IS}"""),
    ("BSD-2-Clause", f"BSD 2-Clause License. Copyright (c) All rights reserved. {_BSD} {_BSD_AS_IS}"),
    ("BSD-3-Clause", f"BSD 3-Clause License. Copyright (c) All rights reserved. {_BSD} {_BSD_NAMES} {_BSD_AS_IS}"),
    ("BSD-3-Clause", _BSD_NAMES),
    ("ISC", """ISC License. Copyright (c) Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided
that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH
REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT,
OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS
ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""),
    ("Zlib", """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the
use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it
freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software.
If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be
plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution."""),
    ("Unlicense", """This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this
software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."""),
    ("Apache-2.0", """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy
of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is
distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing
permissions and limitations under the License."""),
    ("GPL-2.0", _GNU.format(name="General", n=2)),
    ("GPL-3.0", _GNU.format(name="General", n=3)),
    ("LGPL-3.0", _GNU.format(name="Lesser General", n=3)),
    ("AGPL-3.0", _GNU.format(name="Affero General", n=3)),
    ("GPL-3.0", """GNU GENERAL PUBLIC LICENSE Version 3, 29 June 2007 Copyright (C) 2007 Free Software Foundation, Inc. Everyone is permitted to copy and distribute verbatim
copies of this license document, but changing it is not allowed."""),
    ("MPL-2.0", """This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can
obtain one at https://mozilla.org/MPL/2.0/."""),
)
THRESHOLD = 0.7
#: A passage that has no term beginning with one of these names no licensing.
KEYWORDS = ("licen", "copyright", "copyleft", "rights", "redistribut", "permission", "permit", "warrant", "domain")
_TERM = r"[a-z0-9]+"
_COMMENT = r"^\s*(#|//|/?\*|--|;|%|<!--)"
#: Directories that have a licence are broadcast up to this many; beyond, hot directories are dealt out by salt.
BROADCAST_DIRS, SALTS = 200_000, 32


def weights(templates=TEMPLATES) -> tuple[dict[str, float], float, list[tuple[str, dict[str, float], float]]]:
    """Inverse document frequencies over the templates, that of an unlisted term, and (name, weights, norm) of each."""
    bags = [(name, Counter(re.findall(_TERM, text.lower()))) for name, text in templates]
    seen = Counter(t for _, b in bags for t in b)
    idf = {t: math.log((1 + len(bags)) / n) for t, n in seen.items()}
    vectors = []
    for name, bag in bags:
        w = {t: n * idf[t] for t, n in bag.items()}
        vectors.append((name, w, math.sqrt(sum(x * x for x in w.values()))))
    return idf, math.log(1 + len(bags)), vectors


def _literal_map(values: dict[str, float]) -> Column:
    return F.create_map(*[F.lit(x) for kv in sorted(values.items()) for x in kv])


def passages(text: Column) -> Column:
    """The whole text, then its header (comment lines at its start), paragraphs, lines, windows of two and three lines, and
    sentences over line ends."""
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(r"\S"))
    windows = [F.transform(lines, lambda x, i: F.concat_ws(" ", F.slice(lines, i + 1, F.lit(k)))) for k in (2, 3)]
    sentences = F.split(F.regexp_replace(text, r"\s+", " "), r"(?<=[.!?;:]) ")
    after = F.array_position(F.transform(lines, lambda x: x.rlike(_COMMENT)), False)
    header = F.concat_ws(" ", F.slice(lines, F.lit(1), F.when(after == 0, F.size(lines)).otherwise(after - 1).cast("int")))
    return F.array_distinct(F.concat(F.array(text, header), F.split(text, r"\n[ \t#*/;-]*\n"), lines, *windows, sentences))


def own_licenses(files: DataFrame, *, id_col: str = "id", text_col: str = "text", templates=TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """``id, license, cosine, whole``: each row's best passage; null where none reaches the threshold. Ties: first name.

    ``whole``: the text as a whole reaches the threshold. Null and empty texts have no licence; texts are read whole;
    repeated rows give repeated results; other columns are ignored; an empty table gives an empty result.
    """
    idf, rare, vectors = weights(templates)
    names_it = r"\b(" + "|".join(KEYWORDS) + ")"
    table = _literal_map(idf)
    plain = files.select(quoted(id_col).alias("id"), F.lower(F.coalesce(quoted(text_col), F.lit(""))).alias("t"))
    # each step is a column of its own, so nothing is computed once per template; most texts name no licensing
    any_word = F.lit(False)
    for word in KEYWORDS:
        any_word = any_word | F.contains("t", F.lit(word))
    kept = F.filter(passages(F.col("t")), lambda x: x.rlike(names_it))
    lined = plain.select("id", "t", F.when(any_word, kept).alias("p")).select("id", "p", (F.get("p", F.lit(0)) == F.col("t")).alias("whole"))
    terms = lined.select("id", "whole", F.transform("p", lambda x: F.array_sort(F.regexp_extract_all(x, F.lit(_TERM), F.lit(0)))).alias("terms"))
    # of sorted terms, the places where a new one begins: counting takes no second pass over the passage
    starts = lambda a: F.filter(F.sequence(F.lit(0), F.size(a) - 1), lambda i: (i == 0) | (F.get(a, i) != F.get(a, i - 1)))
    runs = terms.select("id", "whole", F.transform("terms", lambda a: F.struct(a.alias("a"), starts(a).alias("s"))).alias("runs"))

    def weighed(r: Column) -> Column:
        count = lambda s, k: F.coalesce(F.get(r["s"], k + 1), F.size(r["a"])) - s
        return F.transform(r["s"], lambda s, k: F.struct(F.get(r["a"], s).alias("t"), (count(s, k) * F.coalesce(F.element_at(table, F.get(r["a"], s)), F.lit(rare))).alias("w")))

    sparse = runs.select("id", "whole", F.transform("runs", weighed).alias("lines"))
    normed = sparse.select("id", "whole", F.transform("lines", lambda v: F.struct(v.alias("v"), F.sqrt(F.aggregate(v, F.lit(0.0), lambda a, x: a + x["w"] * x["w"])).alias("n"))).alias("lines"))

    def cosines(own: Column, norm: float) -> Column:
        return F.transform("lines", lambda y: F.round(F.aggregate(y["v"], F.lit(0.0), lambda a, x: a + x["w"] * F.coalesce(F.element_at(own, x["t"]), F.lit(0.0))) / (y["n"] * norm), 6))

    scores = normed.select("id", "whole", F.array(*[cosines(_literal_map(w), n) for _, w, n in vectors]).alias("c"))
    names = F.array(*[F.lit(name) for name, *_ in vectors])
    best = F.array_min(F.transform("c", lambda c, i: F.struct((-F.coalesce(F.array_max(c), F.lit(0.0))).alias("c"), F.get(names, i).alias("name"))))
    is_whole = F.col("whole") & (F.array_max(F.transform("c", lambda c: F.get(c, F.lit(0)))) >= threshold)
    out = scores.select("id", best.alias("s"), F.coalesce(is_whole, F.lit(False)).alias("whole"))
    hit = F.col("s.c") <= -threshold
    return out.select("id", F.when(hit, F.col("s.name")).alias("license"), F.when(hit, -F.col("s.c")).alias("cosine"), "whole")


def directories(path: Column) -> Column:
    """All directories above a path, the root as the empty string."""
    parts = F.split(path, "/")
    return F.transform(F.sequence(F.lit(0), F.greatest(F.size(parts) - 1, F.lit(0))), lambda i: F.when(i == 0, F.lit("")).otherwise(F.array_join(F.slice(parts, 1, i), "/")))


def parent(path: Column) -> Column:
    return F.when(F.instr(path, "/") > 0, F.regexp_replace(path, "/[^/]*$", "")).otherwise(F.lit(""))


def inherit(files: DataFrame, directory_licenses: DataFrame) -> DataFrame:
    """Add ``effective`` and ``from_dir`` to ``files(id, path, license, ...)``.

    A file's own licence holds; else that of the nearest directory above that ``directory_licenses(dir, dir_license)``
    lists (one row a directory). Each distinct directory is resolved once; the resolved ones are broadcast up to a
    checked number, so files stay where they are, and beyond it they meet files by directory and salt, so that a
    directory with very many files is no one task's. A null path has no directory.
    """
    dirs = files.where(F.col("license").isNull() & F.col("path").isNotNull()).select(parent(F.col("path")).alias("own")).distinct()
    above = dirs.select("own", F.explode(F.array_union(directories(F.concat("own", F.lit("/"))), F.array("own"))).alias("dir"))
    near = above.join(directory_licenses, "dir").groupBy("own").agg(F.max(F.struct(F.length("dir").alias("n"), F.col("dir"), F.col("dir_license"))).alias("m")).select("own", F.col("m.dir").alias("near_dir"), F.col("m.dir_license").alias("near_license"))
    near = cut(near, "near-directories")
    placed = files.withColumn("own", parent(F.col("path")))
    if near.count() <= BROADCAST_DIRS:
        joined = placed.join(F.broadcast(near), "own", "left")
    else:
        salted = near.withColumn("salt", F.explode(F.array(*[F.lit(i) for i in range(SALTS)])))
        joined = placed.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(SALTS)).cast("int")).join(salted, ["own", "salt"], "left").drop("salt")
    none = F.col("license").isNull()
    return joined.withColumn("effective", F.coalesce("license", "near_license")).withColumn("from_dir", F.when(none & F.col("near_license").isNotNull(), F.col("near_dir"))).drop("own", "near_dir", "near_license")


def scan(files: DataFrame, *, id_col: str = "id", path_col: str = "path", text_col: str = "text", templates=TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """``id, path, license, cosine, licence_file, effective, from_dir`` of every file.

    A licence file is one whose text is a licence as a whole, or whose base name is LICENSE, LICENCE, COPYING or NOTICE
    (any ending) and that has a licence; of several in a directory the least path and id counts. Null and empty texts
    have no licence of their own; repeated rows give repeated results; an empty table gives an empty result; other
    columns are ignored.
    """
    named = F.coalesce(F.regexp_extract(quoted(path_col), "[^/]*$", 0).rlike(r"(?i)^(licen[sc]e|copying|notice)([.-].*)?$"), F.lit(False))
    plain = files.select(F.struct(quoted(id_col).alias("id"), quoted(path_col).alias("path"), named.alias("named")).alias("key"), quoted(text_col).alias("text"))
    found = own_licenses(plain, id_col="key", text_col="text", templates=templates, threshold=threshold)
    found = cut(found.select("id.id", "id.path", "license", "cosine", (F.col("license").isNotNull() & (F.col("id.named") | F.col("whole"))).alias("licence_file")), "licenses")
    listed = found.where(F.col("licence_file") & F.col("path").isNotNull()).groupBy(parent(F.col("path")).alias("dir")).agg(F.min(F.struct("path", "id", "license")).alias("m")).select("dir", F.col("m.license").alias("dir_license"))
    return inherit(found, listed).select("id", "path", "license", "cosine", "licence_file", "effective", "from_dir")
