"""Licence scan in DataFrame functions alone: Dice coefficient over word bigrams against licence templates.

Texts are lowered and words are runs of letters and digits, whatever lines they stand in. A template-sized window of words slides over
the text, so a notice may run over lines and a body may be a part of a longer document. A coefficient of t between sets of sizes a and b
needs t (a + b) / 2 common bigrams, at least t / (2 - t) of the template's: a document of fewer words, or a window with fewer of the
template's bigrams, drops out by its sizes alone, and only windows that begin and end at such bigrams are rated.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Notices as they stand in single lines.
NOTICES = {
    "MIT": ["Released under the MIT License.", "Licensed under the MIT License.", "This project is licensed under the terms of the MIT license."],
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0.", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License."],
    "GPL-2.0": ["This work is licensed under the GNU General Public License, version 2.", "Licensed under the GNU GPL v2."],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3.", "Licensed under the GNU GPL v3."],
    "LGPL-3.0": ["This library is licensed under the GNU Lesser General Public License, version 3."],
    "AGPL-3.0": ["This work is licensed under the GNU Affero General Public License, version 3."],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."],
    "BSD-3-Clause": ["Released under the 3-clause BSD License.", "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file."],
    "BSD-2-Clause": ["Released under the 2-clause BSD License."],
    "CC-BY-4.0": ["Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "CC-BY-SA-4.0": ["Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "CC0-1.0": ["Released under CC0 1.0 Universal.", "To the extent possible under law, the author has waived all copyright and related rights to this work."],
    "Unlicense": ["This is free and unencumbered software released into the public domain."],
}
#: Licence bodies, and the headers that stand for long ones in files.
BODIES = {
    "Apache-2.0": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "GPL-2.0": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program; if not, write to the Free Software Foundation, Inc., 51 Franklin Street, Fifth Floor, Boston, MA 02110-1301, USA.",
    "GPL-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program. If not, see <https://www.gnu.org/licenses/>.",
    "LGPL-3.0": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 3 of the License, or (at your option) any later version. This library is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU Lesser General Public License for more details.",
    "AGPL-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU Affero General Public License for more details.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.",
    "BSD-3-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "Unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "Zlib": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",
    "BSD-2-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
}
_WORD = r"[\p{L}\p{N}]+"
#: Templates go into each task's plan as constants; more bytes than this are refused.
MOST_TEMPLATE_BYTES = 4 << 20


def once(value: Column, body: Callable[[Column], Column]) -> Column:
    """body of a value that is computed once, however often body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words_of(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(_WORD), 0)


def _python_words(text: str) -> list[str]:
    import re

    return re.findall(r"[^\W_]+", text.lower())


def _pairs(words: list[str]) -> list[str]:
    return [" ".join(p) for p in zip(words, words[1:], strict=False)]


@dataclass(frozen=True)
class Template:
    """A licence's wording: name, notice or body, words, and its distinct bigrams."""

    licence: str
    unit: str
    words: int
    bigrams: tuple[str, ...]


def _templates(notices: dict[str, list[str]], bodies: dict[str, str]) -> list[Template]:
    texts = [(name, "notice", t) for name, lines in sorted(notices.items()) for t in lines] + [(name, "body", t) for name, t in sorted(bodies.items())]
    found = [Template(name, unit, len(w), tuple(sorted(set(_pairs(w))))) for name, unit, t in texts if len(w := _python_words(t)) > 1]
    if sum(len(b) for t in found for b in t.bigrams) > MOST_TEMPLATE_BYTES:
        raise ValueError("too many licence templates for constants; scan them in parts")
    return found


def bigrams_needed(t: Template, least: float) -> int:
    """The least number of a template's bigrams that a window of any size must hold."""
    return math.ceil(least * len(t.bigrams) / (2 - least) - 1e-9)


def best_first(places: Column, reach: Column | int, touch: Callable[[Column, Column], Column], rank: Callable[[Column], Column]) -> Column:
    """Of places in order of their starts those that taking the best, dropping what touches it, and so on leaves.

    Each round takes every place that is better than all it touches, which are at most `reach` places away.
    """
    none = F.filter(places, lambda x: F.lit(False))

    def around(xs: Column, i: Column) -> Column:
        return F.slice(xs, F.greatest(i + 1 - reach, F.lit(1)), 2 * reach + 1)

    def settle(left: Column) -> Column:
        flags = F.transform(left, lambda x, i: F.struct(x.alias("x"), (~F.exists(around(left, i), lambda y: touch(x, y) & (rank(y) > rank(x)))).alias("best")))
        return once(flags, lambda fs: F.struct(
            F.transform(F.filter(fs, lambda f: f["best"]), lambda f: f["x"]).alias("kept"),
            F.transform(F.filter(fs, lambda f, i: ~F.exists(around(fs, i), lambda g: g["best"] & touch(f["x"], g["x"]))), lambda f: f["x"]).alias("left"),
        ))

    def step(done: Column, _: Column) -> Column:
        more = once(settle(done["left"]), lambda new: F.struct(F.concat(done["kept"], new["kept"]).alias("kept"), new["left"].alias("left")))
        return F.when(F.size(done["left"]) == 0, done).otherwise(more)

    rounds = F.sequence(F.lit(1), F.greatest(F.size(places), F.lit(1)))
    return F.aggregate(rounds, F.struct(none.alias("kept"), places.alias("left")), step, lambda done: done["kept"])


def _rated(words: Column, hits: Column, t: Column, least: float) -> Column:
    """array(struct(dice, start, end, id)) of a text's best windows for a template, no two of which share more than half of it.

    hits(at, code): the places of the words that begin a bigram of some template. Windows begin at a hit, and a window is rated if enough hits lie in it.
    """
    def of_own(own: Column) -> Column:
        def rate(h: Column, i: Column) -> Column:
            inside = F.filter(F.slice(own, i + 1, t["words"] - 1), lambda x: x["at"] < h["at"] + t["words"] - 1)
            window = F.slice(words, h["at"] + 1, t["words"])
            pairs = lambda w: F.size(F.array_distinct(F.zip_with(F.slice(w, 1, F.greatest(F.size(w) - 1, F.lit(0))), F.slice(w, 2, F.greatest(F.size(w) - 1, F.lit(0))), lambda a, b: F.concat(a, F.lit(" "), b))))
            common = lambda x: F.size(F.array_distinct(F.transform(x, lambda y: y["code"])))
            dice = F.round(2 * once(inside, common) / (once(window, pairs) + F.size(t["codes"])), 6)
            enough = F.try_element_at(own, i + t["need"])["at"] < h["at"] + t["words"] - 1
            return F.when(enough, F.struct(dice.alias("dice"), h["at"].alias("start"), (h["at"] + t["words"]).alias("end"), t["id"].alias("id")))

        # Two windows of one template touch if they share more than half of it; so many can begin within that reach.
        touch = lambda x, y: 2 * F.abs(y["start"] - x["start"]) < t["words"]
        return best_first(F.filter(F.transform(own, rate), lambda x: x["dice"] >= least), t["words"], touch, lambda x: F.struct(x["dice"], -x["start"]))

    own = F.filter(hits, lambda h: F.array_contains(t["codes"], h["code"]))
    return F.when(F.size(hits) >= t["need"], once(own, of_own)).otherwise(F.array().cast("array<struct<dice:double,start:int,end:int,id:int>>"))


def scan_licences(docs: DataFrame, notices: dict[str, list[str]] | None = None, bodies: dict[str, str] | None = None, least: float = 0.8) -> DataFrame:
    """(doc_id, unit, line, licence, dice, first_word, end_word): the places of docs(doc_id, text) that match a notice or a body; `line` is where a place begins.

    Of places that touch the one of highest coefficient stays. Null and empty texts match nothing; repeated rows are each
    reported; an empty table gives no rows. Other columns are ignored.
    """
    templates = _templates(notices if notices is not None else NOTICES, bodies if bodies is not None else BODIES)
    docs = docs.select("doc_id", "text").where("text is not null")
    if not templates:
        return docs.select("doc_id", F.lit("").alias("unit"), F.lit(0).alias("line"), F.lit("").alias("licence"), F.lit(0.0).alias("dice"), F.lit(0).alias("first_word"), F.lit(0).alias("end_word")).limit(0)
    held = sorted({b for t in templates for b in t.bigrams})
    code = {b: i + 1 for i, b in enumerate(held)}
    known = F.array(*[F.struct(F.lit(i).alias("id"), F.lit(t.words).alias("words"), F.lit(bigrams_needed(t, least)).alias("need"), F.lit([code[b] for b in t.bigrams]).alias("codes")) for i, t in enumerate(templates)])
    fewest = min(bigrams_needed(t, least) for t in templates)
    # Places of one template lie half of it apart, so no more than these touch one place.
    longest = max(t.words for t in templates)
    reach = sum(2 * -(-2 * longest // t.words) + 2 for t in templates)
    constants = F.lit(held)

    def hits_of(words: Column) -> Column:
        pairs = F.zip_with(F.slice(words, 1, F.greatest(F.size(words) - 1, F.lit(0))), F.slice(words, 2, F.greatest(F.size(words) - 1, F.lit(0))), lambda a, b: F.concat(a, F.lit(" "), b))
        return F.array_compact(F.transform(pairs, lambda p, i: F.when(p.isin(held), F.struct(i.alias("at"), F.array_position(constants, p).cast("int").alias("code")))))

    def of_words(words: Column) -> Column:
        # On equal coefficients the longer place, then that of the later template stays.
        touch = lambda x, y: (y["start"] < x["end"]) & (x["start"] < y["end"])
        rank = lambda x: F.struct(x["dice"], (x["end"] - x["start"]), x["id"], -x["start"])
        in_order = lambda found: F.array_sort(F.transform(found, lambda x: F.struct(x["start"].alias("start"), x["dice"].alias("dice"), x["end"].alias("end"), x["id"].alias("id"))))
        settled = lambda found: once(in_order(found), lambda xs: best_first(xs, reach, touch, rank))
        rated = lambda hits: F.when(F.size(hits) >= fewest, settled(F.flatten(F.transform(known, lambda t: _rated(words, hits, t, least)))))
        return once(hits_of(words), rated)

    # A text of n bigrams has 2n + 1 characters at least.
    places = F.when(F.char_length("text") > 2 * fewest, once(words_of(F.col("text")), of_words))
    lines = F.transform(F.split("text", "\n"), lambda x: F.size(words_of(x)))
    found = docs.select("doc_id", "text", places.alias("places")).where(F.size("places") > 0).select("doc_id", "places", lines.alias("lines"))
    # The line of a word is the number of lines that end before it.
    line = lambda at: F.aggregate("lines", F.struct(F.lit(0).alias("words"), F.lit(0).alias("line")), lambda s, n: F.struct((s["words"] + n).alias("words"), (s["line"] + (s["words"] + n <= at).cast("int")).alias("line")), lambda s: s["line"])
    rows = found.select("doc_id", "lines", F.explode("places").alias("place"))
    named = [F.element_at(F.lit([getattr(t, k) for t in templates]), F.col("place.id") + 1).alias(k) for k in ("unit", "licence")]
    return rows.select("doc_id", named[0], line(F.col("place.start")).alias("line"), named[1], "place.dice", F.col("place.start").alias("first_word"), F.col("place.end").alias("end_word"))
