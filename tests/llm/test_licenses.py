"""License recognition on whole license texts, and against a matcher that tries everything."""

import random

import pytest

pytest.importorskip("rulefeat.llm")

from rulefeat.llm import license_rules as lic  # noqa: E402

MIT = '''MIT License

Copyright (c) 2020 Some One

Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER
LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,
OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE
SOFTWARE.
'''
APACHE = '''/*
 * Licensed under the Apache License, Version 2.0 (the "License");
 * you may not use this file except in compliance with the License.
 * You may obtain a copy of the License at
 *
 *     http://www.apache.org/licenses/LICENSE-2.0
 *
 * Unless required by applicable law or agreed to in writing, software
 * distributed under the License is distributed on an "AS IS" BASIS,
 * WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
 * See the License for the specific language governing permissions and
 * limitations under the License.
 */
'''
BSD3 = '''Copyright (c) 2011, Some People
All rights reserved.

Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this
   list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation
   and/or other materials provided with the distribution.

3. Neither the name of the copyright holder nor the names of its
   contributors may be used to endorse or promote products derived from
   this software without specific prior written permission.

THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS"
AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE
IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE
DISCLAIMED.
'''
BSD2 = BSD3[: BSD3.index("3. Neither")] + BSD3[BSD3.index("THIS SOFTWARE") :]
GPL = '''# This program is free software; you can redistribute it and/or modify
# it under the terms of the GNU General Public License as published by
# the Free Software Foundation; either version 2 of the License, or
# (at your option) any later version.
#
# This program is distributed in the hope that it will be useful,
# but WITHOUT ANY WARRANTY; without even the implied warranty of
# MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.
'''
MPL = '''/* This Source Code Form is subject to the terms of the Mozilla Public
 * License, v. 2.0. If a copy of the MPL was not distributed with this
 * file, You can obtain one at https://mozilla.org/MPL/2.0/. */'''
ISC = '''Permission to use, copy, modify, and/or distribute this software for any
purpose with or without fee is hereby granted, provided that the above
copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES
WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF
MERCHANTABILITY AND FITNESS.'''
BODY = '''                                 Apache License
                           Version 2.0, January 2004
                        http://www.apache.org/licenses/

   TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION

   1. Definitions.

      "License" shall mean the terms and conditions for use, reproduction,
      and distribution as defined by Sections 1 through 9 of this document.
'''
WHOLE = [
    (MIT, ["MIT"]), (APACHE, ["Apache-2.0"]), (BSD3, ["BSD-3-Clause"]), (BSD2, ["BSD-2-Clause"]), (GPL, ["GPL-2.0-or-later"]), (MPL, ["MPL-2.0"]), (ISC, ["ISC"]), (BODY, ["Apache-2.0"]),
    (GPL.replace("software;", "software:").replace("Foundation;", "Foundation,").replace("version 2", "version 3"), ["GPL-3.0-or-later"]),
    (GPL.replace("General Public", "Lesser General Public").replace("version 2", "version 2.1").replace("program", "library"), ["LGPL-2.1-or-later"]),
    (GPL.replace("General Public", "Affero General Public").replace("version 2", "version 3"), ["AGPL-3.0-or-later"]),
    ("// SPDX-License-Identifier: GPL-2.0-or-later WITH Classpath-exception-2.0 OR MIT\nint x;", ["GPL-2.0-or-later", "MIT"]),
    ("/* SPDX-License-Identifier: (MIT AND BSD-3-Clause) */", ["MIT", "BSD-3-Clause"]), ("# spdx-license-identifier: apache-2.0", ["apache-2.0"]),
    ("This work is licensed under the GNU General Public License, version 3.", ["GPL-3.0"]), ("All rights reserved.", ["Proprietary"]), ("All rights reserved. Licensed under CC BY 4.0", ["CC-BY-4.0"]),
    ("Licensed under CC BY 4.0. All rights reserved.", ["CC-BY-4.0", "Proprietary"]), ("prose\nReleased under the MIT License\nand more prose", ["MIT"]), ("a license plate in the public domain of free software", []),
    ("This is free and unencumbered software released into the public domain.", ["Unlicense"]), ("", []), (None, []), ("licensed " * 50_000, []),
]


@pytest.mark.parametrize("case", range(len(WHOLE)))
def test_whole_license_texts(case):
    text, want = WHOLE[case]
    assert [n for _, _, n in lic.rule_book().find(text)] == want
    assert all(0 <= a < b <= len(text) for a, b, _ in lic.rule_book().find(text))


def ends(parts, words, breaks, i):
    """All places where the parts can end from word i on, the fewest unnamed words first."""
    if not parts:
        yield i
        return
    p, rest = parts[0], parts[1:]
    if isinstance(p, int):
        for k in range(p + 1):
            if i + k > len(words) or (p == 8 and k and (i + k == len(words) or breaks[i + k] != " ")):
                return
            yield from ends(rest, words, breaks, i + k)
        return
    forms, optional = p
    if i < len(words) and (any(w == words[i] or (w == "{num}" and words[i][0].isdigit() and words[i].replace(".", "").isdigit()) for w in forms)):
        yield from ends(rest, words, breaks, i + 1)
    if optional:
        yield from ends(rest, words, breaks, i)


def slow_identify(words, breaks, known=lic.SENTENCES):
    found = []
    for order, (name, sentence) in enumerate(known.items()):
        parts = sentence.split()
        shape = []
        for k, p in enumerate(parts):
            if p == "...":
                shape.append(8 if k == 0 else 60 if k == len(parts) - 1 else 40)
            else:
                shape.append((p.rstrip("?").split("|"), p.endswith("?")))
        i = 0
        while i < len(words):
            end = None
            if breaks[i] != " ":
                for e in ends(shape, words, breaks, i):
                    if e > i and (e == len(words) or breaks[e] != " ") and lic.HARD not in breaks[i + 1 : e]:
                        end = e
                        break
            if end is None:
                i += 1
            else:
                num = next((w for w in words[i:end] if w[0].isdigit()), None) if "{num}" in sentence else None
                found.append((i, -end, order, name, num))
                i = end
    out, last = [], 0
    for first, end, _, name, num in sorted(found, key=lambda f: f[:3]):
        if first >= last:
            out.append((first, -end, name, num))
            last = -end
    return out


def slow_rules(row, gap=1):
    """Names by trying every rule from every one of its possible first sentences."""
    out, i = [], 0
    while i < len(row):
        best = None
        for place, (name, wanted) in enumerate(lic.RULES):
            for skip in range(len(wanted)):
                if all(w.endswith("?") for w in wanted[:skip]) and row[i][2] == wanted[skip].rstrip("?"):
                    at, n, num, ok = i, 1, row[i][3], True
                    for w in wanted[skip + 1 :]:
                        k = next((k for k in range(at + 1, at + 2 + gap) if k < len(row) and row[k][2] == w.rstrip("?") and row[k][0] - row[at][1] <= lic.WORDS_BETWEEN), None)
                        if k is None:
                            ok = ok and w.endswith("?")
                        else:
                            at, n, num = k, n + 1, num or row[k][3]
                    if ok and (best is None or (-n, place) < best[:2]):
                        best = (-n, place, at, lic.named(name, num))
        if best:
            out.append(best[3])
            i = best[2]
        i += 1
    return [n for k, n in enumerate(out) if n != lic.LAST_RESORT or not any(x != lic.LAST_RESORT for x in out[k + 1 :])]


def test_sentences_and_rules_equal_brute_force():
    draw, book = random.Random(6), lic.rule_book()
    flat = [s.replace("{num}", "2.0").replace("...", "some words") for s in lic.SENTENCES.values()]
    for _ in range(60):
        text = ""
        for _ in range(draw.randrange(1, 7)):
            words = [draw.choice(w.rstrip("?").split("|")) for w in draw.choice(flat).split() if not w.endswith("?") or draw.random() < 0.5]
            if draw.random() < 0.2:
                words[draw.randrange(len(words))] = "other"
            text += "".join(w + draw.choice([" ", " ", " ", ", ", "\n * "]) for w in words) + draw.choice([".\n", ". ", "\n", "\n\n", "; ", " "])
        words, breaks, _ = lic.words_of(text)
        assert book.identify(words, breaks) == slow_identify(words, breaks), text
        assert [n for _, _, n in book.find(text)] == slow_rules(slow_identify(words, breaks)), text


def test_results_do_not_hang_on_hash_order():
    import os
    import subprocess
    import sys

    code = "from rulefeat.llm import license_rules as l; print([l.rule_book().find(' '.join(x.replace('...', 'of a').replace('{num}', '2.0').replace('?', '').split('|')[0] for x in s.split()) + '.') for s in l.SENTENCES.values()])"
    top = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    seen = {subprocess.run([sys.executable, "-c", code], check=True, capture_output=True, cwd=top, env=os.environ | {"PYTHONHASHSEED": str(n)}).stdout for n in (0, 1, 2)}
    assert len(seen) == 1


def test_the_longest_form_wins():
    book = lic.rule_book()
    assert [n for _, _, n in book.find("Licensed under CC BY-NC-SA 4.0.")] == ["CC-BY-NC-SA-4.0"]
    assert [n for _, _, n in book.find(BSD3.replace("3. Neither", "3. All advertising materials mentioning features or use of this software must display the following acknowledgement: hello.\n\n4. Neither"))] == ["BSD-4-Clause"]
