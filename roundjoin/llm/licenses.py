"""Licence scans: normalised text compared to licence templates by the Dice coefficient over word bigrams; size bounds prune candidate templates.
DataFrame functions only, without a shuffle: what is broadcast are the templates, which are code.

Both sides are bags of bigrams, so a stretch of w words has exactly w - 1 bigrams and its word count alone says which templates can reach the threshold.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Callable
from fractions import Fraction

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import pick

#: Production value.
THRESHOLD = 0.8
_MIT_TERMS = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the
Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit
persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or
substantial portions of the Software."""
_AS_IS = """THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A
PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT
OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
_BSD_TERMS = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of
source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice,
this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."""
_BSD_NAMES = """3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior
written permission."""
_BSD_AS_IS = """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF
MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL,
EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED
AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF
THE POSSIBILITY OF SUCH DAMAGE."""
#: Licence, form, wording.
TEMPLATES = (
    ("MIT", "notice", "Released under the MIT License."),
    ("MIT", "notice", "Licensed under the MIT License."),
    ("MIT", "text", _MIT_TERMS + " " + _AS_IS),
    ("MIT", "terms", _MIT_TERMS),
    ("Apache-2.0", "notice", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "header", """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the
License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS,
WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."""),
    ("GPL-3.0", "notice", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "header", """This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software
Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even
the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."""),
    ("CC-BY-NC-4.0", "notice", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "notice", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC-BY-4.0", "notice", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "notice", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "notice", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("BSD-3-Clause", "notice", "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file."),
    ("BSD-3-Clause", "text", f"{_BSD_TERMS} {_BSD_NAMES} {_BSD_AS_IS}"),
    ("BSD-2-Clause", "text", f"{_BSD_TERMS} {_BSD_AS_IS}"),
    ("MPL-2.0", "header", """This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one
at http://mozilla.org/MPL/2.0/."""),
    ("ISC", "terms", """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and
this permission notice appear in all copies."""),
    ("Unlicense", "text", """This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software,
either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."""),
)


def template_bigrams(text: str) -> Counter:
    """Bag of word bigrams of a normalised template."""
    words = re.findall(r"[^\W_]+", text.lower())
    return Counter(zip(words, words[1:], strict=False))


def size_range(size: int, threshold: float) -> tuple[int, int]:
    """Bag sizes whose Dice coefficient with a bag of this size can reach the threshold."""
    t = Fraction(str(threshold))
    return math.ceil(size * t / (2 - t)), math.floor(size * (2 - t) / t)


def anchors(bag: Counter, threshold: float) -> list[str]:
    """Words of which every stretch that reaches the threshold holds one.

    Such a stretch lacks at most a share 1 - t / (2 - t) of the bag, so words that touch more of its bigrams than that can't all be absent. Taken first are
    the words that touch the most bigrams for how common words of their length are."""
    left = sum(bag.values()) - size_range(sum(bag.values()), threshold)[0] + 1
    open_, out = Counter(bag), []
    while left > 0:
        touch = Counter()
        for pair, n in open_.items():
            for w in set(pair):
                touch[w] += n
        best = max(touch, key=lambda w: (touch[w] * min(len(w), 9) ** 2 * (len(w) > 4 or 0.01), w))
        out.append(best)
        left -= touch[best]
        open_ = Counter({pair: n for pair, n in open_.items() if best not in pair})
    return out


def _matches(hits: Column, bag: Counter, threshold: float) -> Column:
    """Stretches of a text that reach the threshold with a template's bag, as structs of minus the Dice coefficient, first and last bigram.

    hits: the text's bigrams of any template (b) with their places (i), in order. A stretch is best cut to begin and end with bigrams of the bag, so only those
    are tried, the best end for each begin. A bigram in the bag n times counts in a stretch unless n of its copies stand before it there."""
    size = sum(bag.values())
    lo, hi = size_range(size, threshold)
    several = {n: [" ".join(b) for b, m in bag.items() if m == n] for n in sorted(set(bag.values()) - {1})}

    def copies(b: Column) -> Column:
        out = F.lit(1)
        for n, those in several.items():
            out = F.when(b.isin(those), n).otherwise(out)
        return out

    def placed(h: Column) -> Column:
        """Places, each with that of the copy that must stand before a stretch for this one to count in it."""
        same = lambda x, k: F.filter(F.slice(h, F.greatest(k - hi, F.lit(0)) + 1, F.least(k, F.lit(hi))), lambda y: y["b"] == x["b"])
        return F.transform(h, lambda x, k: F.struct(x["i"].alias("i"), F.coalesce(F.try_element_at(same(x, k), -copies(x["b"]))["i"], F.lit(-1)).alias("after")))

    def stretches(q: Column) -> Column:
        def best(x: Column, k: Column) -> Column:
            counted = F.filter(F.slice(q, k + 1, F.lit(hi)), lambda y: (y["i"] < x["i"] + hi) & (y["after"] < x["i"]))
            ends = F.transform(counted, lambda y, c: F.struct((-2.0 * (c + 1) / (y["i"] - x["i"] + 1 + size)).alias("minus"), x["i"].alias("first"), y["i"].alias("last")))
            return F.when(dense(q, x, k), F.array_min(ends))

        return F.filter(F.transform(q, best), lambda z: z["minus"] <= -threshold)

    # a stretch that reaches the threshold has lo bigrams of the bag within hi
    dense = lambda h, x, k: F.coalesce(F.try_element_at(h, k + lo)["i"] < x["i"] + hi, F.lit(False))
    none = F.array().cast("array<struct<minus:double,first:int,last:int>>")
    some = lambda h: (F.size(h) >= lo) & F.exists(F.transform(h, lambda x, k: dense(h, x, k)), lambda z: z)
    own = F.filter(hits, lambda x: x["b"].isin([" ".join(b) for b in bag]))
    return _with(own, lambda h: F.when(some(h), _with(placed(h), stretches)).otherwise(none))


def _with(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value), with the value computed once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _apart(found: Column) -> Column:
    """How many stretches, taken in order, lie behind the one taken before."""
    start = F.struct(F.lit(0).alias("n"), F.lit(-1).alias("last"))
    return F.aggregate(found, start, lambda a, z: F.when(z["first"] > a["last"], F.struct((a["n"] + 1).alias("n"), z["last"].alias("last"))).otherwise(a), lambda a: a["n"])


def scan_licenses(docs: DataFrame, templates: tuple[tuple[str, str, str], ...] = TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """Per row of docs: doc_id, licenses (those found, by name, joined by commas), best_license, best_dice, n_matches.

    Compared with every template are all stretches of consecutive words of the whole text, over borders of lines and paragraphs, whose length its size bound
    admits. n_matches counts for each template the stretches that match without overlap. Null, empty and one-word texts match nothing (best_license and
    best_dice are null, licenses empty); ties go to the first name; repeated rows have a row each; a null doc_id stays; an empty table gives no rows; other
    columns are ignored."""
    bags = [(name, bag) for name, _, text in templates if (bag := template_bigrams(text))]
    rows = pick(docs, "doc_id", "text").select("doc_id", F.lower(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("text"))
    probes = sorted({w for _, bag in bags for w in anchors(bag, threshold)})
    probes = [w for w in probes if not any(v != w and v in w for v in probes)]
    hopeful = _any([F.col("text").contains(w) for w in probes]) if probes else F.lit(False)
    known = sorted({" ".join(b) for _, bag in bags for b in bag})
    words = rows.select("doc_id", F.when(hopeful, F.split("text", r"[^\p{L}\p{N}]+")).alias("w"))
    pairs = F.zip_with("w", F.slice("w", 2, F.greatest(F.size("w") - 1, F.lit(0))), lambda a, b: F.concat_ws(" ", a, b))
    hits = F.filter(F.transform(pairs, lambda b, i: F.when(b.isin(known), F.struct(i.alias("i"), b.alias("b")))), lambda x: x.isNotNull())
    least = min((size_range(sum(bag.values()), threshold)[0] for _, bag in bags), default=1)
    placed = words.select("doc_id", hits.alias("hits")).select("doc_id", F.when(F.size("hits") >= least, F.col("hits")).alias("hits"))

    def summed(name: str) -> Callable[[Column], Column]:
        return lambda z: F.when(F.size(z) > 0, F.struct(F.array_min(F.transform(z, lambda y: y["minus"])).alias("minus"), F.lit(name).alias("name"), _apart(z).alias("n")))

    def scores(hits: Column) -> Column:
        each = [_with(_matches(hits, bag, threshold), summed(name)) for name, bag in bags]
        return F.array_sort(F.filter(F.array(*each), lambda x: x.isNotNull()))

    none = F.array().cast("array<struct<minus:double,name:string,n:int>>")
    done = placed.select("doc_id", (F.when(F.col("hits").isNotNull(), scores(F.col("hits"))).otherwise(none) if bags else none).alias("found"))
    best = F.try_element_at(F.col("found"), F.lit(1))
    names = F.array_sort(F.array_distinct(F.transform("found", lambda x: x["name"])))
    total = F.aggregate("found", F.lit(0), lambda a, x: a + x["n"])
    return done.select("doc_id", F.concat_ws(",", names).alias("licenses"), best["name"].alias("best_license"), (-best["minus"]).alias("best_dice"), total.alias("n_matches"))


def _any(tests: list[Column]) -> Column:
    out = tests[0]
    for t in tests[1:]:
        out = out | t
    return out
