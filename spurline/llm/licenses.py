"""License scans: normalised text against licence templates by the Dice coefficient of word bigrams.

All of it is DataFrame functions. Units of a text are its lines, its paragraphs and the whole, and word windows of a template's
length in lines that match no template as a whole; equal bags of bigrams have
Dice 1. Two bags with sizes a and b can reach t only if t / (2 - t) <= a / b <= (2 - t) / t, so most units drop out by their
number of words. A unit that can reach t shares at least t / (2 - t) of a template's bigrams, so it holds one of a few telling words;
texts and units without any of them need no splitting at all.
"""

from __future__ import annotations

import json
import math
import re
from collections import Counter

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Licence notices, in the words that their publishers give.
TEMPLATES = {
    "apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "apache-2.0-header": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.',
    "cc-by-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "cc-by-nc-4.0": "Licensed under CC BY-NC 4.0.",
    "cc-by-sa-4.0": "Licensed under CC BY-SA 4.0.",
    "gpl-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "gpl-3.0-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "mit": "Released under the MIT License.",
    "mit-grant": 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:',
    "agpl-3.0-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "bsd-style": "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file.",
    "bsd-2-clause": 'Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.',
    "bsd-3-clause": 'Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.',
    "bsd-grant": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "bsd-disclaimer": 'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.',
    "gpl-2.0-header": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 2 of the License, or (at your option) any later version.",
    "gpl-warranty": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    "isc": 'Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.',
    "isc-grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "isc-disclaimer": 'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.',
    "lgpl-2.1-header": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 2.1 of the License, or (at your option) any later version.",
    "lgpl-3.0-header": "This library is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "mit-full": 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.',
    "mit-disclaimer": 'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.',
    "mit-license": "Licensed under the MIT License.",
    "mpl-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "reserved": "All rights reserved.",
}
NOT_WORD = r"[^\p{L}\p{N}\n]+"


def template_bigrams(templates: dict[str, str] = TEMPLATES) -> dict[str, Counter]:
    out = {}
    for name, text in templates.items():
        words = re.sub(r"[^0-9a-z]+", " ", text.lower()).split()
        out[name] = Counter(f"{a} {b}" for a, b in zip(words, words[1:], strict=False))
    if sum(len(x) for x in out.values()) > 20_000:
        raise ValueError("templates of over 20000 bigrams do not belong in a plan")
    return out


def telling_words(bags: dict[str, Counter], low: float) -> list[str]:
    """Words of which every unit that can reach the threshold holds one.

    Such a unit shares at least ``low`` of a template's bigrams. So if words are picked until the bigrams that they touch
    are more than the rest, a unit without any of them shares too few. Longer words are picked first where they suffice.
    """
    out: set[str] = set()
    for bag in bags.values():
        rest, spare = Counter(bag), sum(bag.values()) - math.ceil(low * sum(bag.values()) - 1e-9)
        while rest and sum(bag.values()) - sum(rest.values()) <= spare:
            touched: Counter = Counter()
            for gram, k in rest.items():
                for w in set(gram.split()):
                    touched[w] += k
            pick = max(touched, key=lambda w: (w in out, len(w) >= 6, touched[w], len(w), w))
            out.add(pick)
            rest = Counter({g: k for g, k in rest.items() if pick not in g.split()})
    return sorted(out)


def _held(df: DataFrame, name: str, value: F.Column) -> DataFrame:
    """``df`` with a column that is worked out once for each row: Catalyst copies a plain expression into every predicate that
    uses it, but a generator's output stays as it is."""
    return df.withColumn(name, F.explode(F.array(value)))


def scan_licenses(docs: DataFrame, templates: dict[str, str] = TEMPLATES, threshold: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, unit, unit_no, license, dice)``: the best template of every unit that reaches ``threshold``; ties to the first name.

    Units: ``line`` (numbered from 0), ``paragraph`` (between empty lines, if it has several lines) and ``document`` (if it has
    several paragraphs). A line that matches no template has ``passage`` units under its own number: windows as long as a template,
    placed so that one of its telling words stands where the template has it; of overlapping ones the best is kept, then the
    longest. Normalising lower-cases and turns everything but letters and digits into single spaces. Null and empty
    texts have no units; null ids and repeated rows stay. Nothing is shuffled. ``templates`` need ASCII letters.
    """
    bags = template_bigrams(templates)
    low, high = threshold / (2 - threshold), (2 - threshold) / threshold
    fits, told = F.lit(False), F.lit(False)
    for n in sorted({sum(c.values()) for c in bags.values()}):
        fits = fits | F.col("n").between(F.lit(low * n - 1e-9), F.lit(high * n + 1e-9))
    told_words = telling_words(bags, low)
    for w in told_words:
        told = told | F.contains(F.col("t"), F.lit(f" {w} "))
    clean = F.regexp_replace(F.regexp_replace(F.lower(F.col(text_col).cast("string")), NOT_WORD, " "), "\n", " \n ")
    plain = _held(docs.select(F.col(id_col).cast("long").alias("doc_id"), clean.alias("clean")), "t", F.concat(F.lit(" "), F.col("clean"), F.lit(" ")))
    plain = plain.where(told).select("doc_id", "t")
    split = F.split(F.regexp_replace("t", r"\n *(?:\n *)+", "\u0001"), "\u0001")
    unit = lambda kind, xs: F.transform(xs, lambda x, i: F.struct(F.lit(kind).alias("unit"), i.cast("int").alias("unit_no"), x.alias("t")))
    several = F.filter(unit("paragraph", split), lambda u: F.contains(u["t"], F.lit("\n")))
    whole = F.when(F.size(split) > 1, unit("document", F.array("t"))).otherwise(F.slice(unit("document", F.array("t")), 1, 0))
    rows = plain.select("doc_id", F.explode(F.concat(unit("line", F.split("t", "\n")), several, whole)).alias("u"))
    spaced = F.concat(F.lit(" "), F.trim(F.regexp_replace("u.t", r"[ \n]+", " ")), F.lit(" "))
    rows = _held(rows.select("doc_id", "u"), "t", spaced).select("doc_id", "u.unit", "u.unit_no", "t").where(told)
    size = F.length("t") - F.length(F.translate("t", " ", "")) - 2  # as many bigrams as spaces between words
    longer = (F.col("unit") == "line") & (F.col("n") > min(sum(c.values()) for c in bags.values()))
    rows = _held(rows, "n", size).where((fits | longer) & (F.col("n") > 0)).withColumn("t", F.trim("t"))
    places = {k: [{"w": w, "j": j} for j, w in enumerate(re.sub(r"[^0-9a-z]+", " ", text.lower()).split()) if w in told_words] for k, text in templates.items()}
    shapes = [{"license": k, "m": sum(c.values()), "once": sorted(c), "more": [{"g": g, "k": n} for g, n in sorted(c.items()) if n > 1], "at": places[k]} for k, c in sorted(bags.items())]
    known = F.from_json(F.lit(json.dumps(shapes)), "array<struct<license:string,m:int,once:array<string>,more:array<struct<g:string,k:int>>,at:array<struct<w:string,j:int>>>>")
    rows = rows.select("doc_id", "unit", "unit_no", "n", F.split("t", " ").alias("w"), known.alias("known"))
    # Shared bigrams: the distinct ones by a hash set, and what those that a template has several times add to that.
    shared = """aggregate(array(zip_with(slice(w, {0}, {1}), slice(w, {0} + 1, {1}), (a, b) -> concat(a, ' ', b))), 0, (s, g) -> size(array_intersect(g, x.once))
        + aggregate(x.more, 0, (t, y) -> t + greatest(least(y.k, size(filter(g, z -> z = y.g))) - 1, 0)))"""
    best = F.expr(f"""array_min(filter(transform(filter(known, x -> n between {low!r}D * x.m - 1e-9D and {high!r}D * x.m + 1e-9D),
        x -> struct(-2D * {shared.format("1", "n")} / (n + x.m) as dice, x.license as license)),
        x -> -x.dice >= {threshold!r}D - 1e-12D))""")
    # A window has a telling word at the template's place of it; its size is the template's, so Dice is the share of bigrams.
    windows = F.expr(f"""filter(flatten(transform(filter(known, x -> n > x.m),
        x -> transform(array_distinct(flatten(transform(filter(x.at, a -> array_contains(w, a.w)),
            a -> filter(transform(sequence(1, n + 1), p -> if(element_at(w, p) = a.w, p - a.j, 0)), p -> p between 1 and n + 1 - x.m)))),
            p -> struct({shared.format("p", "x.m")} / double(x.m) as dice, x.m as m, p as p, x.license as license)))),
        x -> x.dice >= {threshold!r}D - 1e-12D)""")
    rows = _held(rows, "best", best)
    rows = _held(rows, "found", F.when((F.col("unit") == "line") & F.col("best").isNull(), windows))
    # Of two windows that overlap, the one with more Dice stays, then the longer, then the first by name and place.
    alone = F.expr("""filter(found, c -> not exists(found, d -> d.p <= c.p + c.m and c.p <= d.p + d.m
        and struct(-d.dice as a, -d.m as b, d.license as c, d.p as d) < struct(-c.dice as a, -c.m as b, c.license as c, c.p as d)))""")
    passages = F.transform(alone, lambda c: F.struct(F.lit("passage").alias("unit"), c["license"].alias("license"), c["dice"].alias("dice")))
    whole_unit = F.array(F.struct("unit", F.col("best.license").alias("license"), (-F.col("best.dice")).alias("dice")))
    rows = rows.select("doc_id", "unit_no", F.explode(F.when(F.col("best").isNotNull(), whole_unit).otherwise(passages)).alias("m"))
    return rows.select("doc_id", "m.unit", "unit_no", "m.license", F.round("m.dice", 6).alias("dice"))
