"""License recognition in two steps: sentences to identifiers, then identifier sequences to licenses.

A text becomes its words, with the breaks between them: a full stop, semicolon, colon, question or exclamation mark before white space, an empty line and a list mark end a
sentence; the end of a line may end one or may be a wrap. Marks of comments, quotes and commas are no words and vanish. Known license sentences, which begin and end at breaks of
either kind, have identifiers; where two overlap the earlier, then the longer one counts. A rule names a license by identifiers in order. Of the rules that
fit at a place that with the most sentences wins, then the earlier in the table; up to `gap` other known sentences and `WORDS_BETWEEN` words may stand between two sentences of a rule.
License expressions after the short-identifier tag are parsed.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from functools import lru_cache

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import ship_package

WORDS_BETWEEN = 80
#: License sentences. {num} is a number; a|b are alternatives; a word with ? may be missing; ... is up to eight words of the same line before, or the words up to the next break after, or up to forty between.
SENTENCES = {
    "apache-grant": "... licensed under the apache license version|v? {num} ...",
    "apache-released": "... released|distributed|available under the? terms? of? the? apache license version|v? {num} ...",
    "apache-file": "you may not use this file except in compliance with the license",
    "apache-copy": "you may obtain a copy of the license at ...",
    "apache-asis": "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    "apache-see": "see the license for the specific language governing permissions and limitations under the license",
    "apache-title": "apache license version {num} ...",
    "apache-terms": "terms and conditions for use reproduction and distribution",
    "apache-definitions": "license shall mean the terms and conditions for use reproduction and distribution as defined by sections 1 through 9 of this document",
    "apache-licensor": "licensor shall mean the copyright owner or entity authorized by the copyright owner that is granting the license",
    "apache-end": "end of terms and conditions",
    "mit-release": "... released|distributed|available under the? terms? of? the mit|expat license",
    "mit-under": "... licensed under the mit|expat license ...",
    "mit-title": "the? mit license mit?",
    "mit-grant": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions",
    "mit-grant-short": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction ...",
    "mit-notice": "the above copyright notice and this permission notice including? the? next? paragraph? shall be included in all copies or substantial portions of the software",
    "mit-asis": "the software is provided as is without warranty of any kind express or implied ...",
    "mit-liability": "in no event shall the authors or copyright holders be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software",
    "isc-title": "the? isc license ...",
    "isc-under": "... licensed|released under the isc license ...",
    "isc-grant": "permission to use copy modify and or? distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    "isc-grant-0": "permission to use copy modify and or? distribute this software for any purpose with or without fee is hereby granted",
    "isc-asis": "the software is provided as is and the? author|isc disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness",
    "bsd-title": "bsd {num} clause license ...",
    "bsd-under": "... licensed|released under the bsd license ...",
    "bsd-under-num": "... licensed|released under the bsd? {num} clause bsd? license ...",
    "bsd-grant": "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    "bsd-source": "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
    "bsd-binary": "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution",
    "bsd-advert": "all advertising materials mentioning features or use of this software must display the following acknowledgement ...",
    "bsd-endorse": "neither the name of ... nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    "bsd-endorse-names": "neither the names? of ... may be used to endorse or promote products derived from this software without specific prior written permission",
    "bsd-endorse-old": "the names? of ... may not be used to endorse or promote products derived from this software without specific prior written permission",
    "bsd-asis": "this software is provided by ... as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed",
    "bsd-liability": "in no event shall ... be liable for any direct indirect incidental special exemplary or consequential damages ...",
    "zlib-asis": "this software is provided as is without any express or implied warranty",
    "zlib-liability": "in no event will the authors be held liable for any damages arising from the use of this software",
    "zlib-grant": "permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions",
    "zlib-origin": "the origin of this software must not be misrepresented ...",
    "boost-title": "boost software license version {num} ...",
    "boost-under": "... distributed|licensed under the boost software license version {num} ...",
    "boost-grant": "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license ...",
    "free-software": "... is free software",
    "gpl-hope": "... is distributed in the hope that it will be useful but without any warranty ...",
    "either-later": "either version {num} of the license or at your option any later version",
    "verbatim": "everyone is permitted to copy and distribute verbatim copies of this license document but changing it is not allowed",
    "cc-nc": "... licensed under cc by nc {num}",
    "cc-nc-sa": "... licensed under cc by nc sa {num}",
    "cc-nc-nd": "... licensed under cc by nc nd {num}",
    "cc-nd": "... licensed under cc by nd {num}",
    "cc-sa": "... licensed under cc by sa {num}",
    "cc-by": "... licensed under cc by {num}",
    "cc-work": "... licensed under a|the creative commons attribution {num} ...",
    "cc-work-sa": "... licensed under a|the creative commons attribution sharealike|share alike? {num} ...",
    "cc-work-nc": "... licensed under a|the creative commons attribution noncommercial|non commercial? {num} ...",
    "cc-work-nc-sa": "... licensed under a|the creative commons attribution noncommercial|non commercial? sharealike|share alike? {num} ...",
    "cc-zero": "... dedicated to the public domain under cc0 {num} ...",
    "cc-zero-under": "... licensed|released under cc0 {num} ...",
    "cc-zero-title": "cc0 {num} universal ...",
    "mpl-grant": "this source code form is subject to the terms of the mozilla public license v|version {num}",
    "mpl-copy": "if a copy of the mpl was not distributed with this file you can obtain one at ...",
    "mpl-title": "mozilla public license version {num}",
    "mpl-under": "... licensed under the mozilla public license version|v? {num} ...",
    "epl-terms": "this program and the accompanying materials are made available under the terms of the eclipse public license v|version {num} which ...",
    "epl-title": "eclipse public license v|version {num}",
    "epl-under": "... licensed under the eclipse public license version|v? {num} ...",
    "artistic-title": "the? artistic license {num} ...",
    "wtfpl-title": "do what the fuck you want to public license ...",
    "unlicense": "this is free and unencumbered software released into the public domain",
    "unlicense-anyone": "anyone is free to copy modify publish use compile sell or distribute this software ...",
    "public-domain": "... released into the public domain",
    "reserved": "all rights reserved",
}
#: The GNU licenses by identifier and the words of their names.
GNU = {"gpl": ("GPL", "general"), "lgpl": ("LGPL", "lesser|library general"), "agpl": ("AGPL", "affero general")}
for _id, (_, _words) in GNU.items():
    _license, _terms = f"gnu {_words} public license", "you can redistribute it and or modify it under the terms of the"
    SENTENCES |= {
        f"{_id}-under": f"... licensed|released|distributed|available under the? terms? of? the {_license} version|v {{num}}",
        f"{_id}-under-later": f"... licensed|released|distributed|available under the? terms? of? the {_license} version|v {{num}} or at? your? option? any? later version?",
        f"{_id}-terms": f"{_terms} {_license} as published by the free software foundation",
        f"{_id}-terms-later": f"{_terms} {_license} as published by the free software foundation either version {{num}} of the license or at your option any later version",
        f"{_id}-terms-num": f"{_terms} {_license} version|v {{num}} as published by the free software foundation",
        f"{_id}-terms-of": f"{_terms} {_license} as published by the free software foundation version {{num}} of the license",
        f"{_id}-title": f"{_license} version {{num}} ...",
    }
#: Licenses by identifiers in order; one with ? may be missing. {num} in a name is the first number in the rule's sentences.
RULES = [
    ("Apache-{num}", ["apache-grant", "apache-file?", "apache-copy?", "apache-asis?", "apache-see?"]),
    ("Apache-{num}", ["apache-released", "apache-file?", "apache-copy?", "apache-asis?", "apache-see?"]),
    ("Apache-{num}", ["apache-title", "apache-terms?", "apache-definitions", "apache-licensor?", "apache-end?", "apache-grant?", "apache-file?", "apache-copy?", "apache-asis?", "apache-see?"]),
    ("Apache-{num}", ["apache-title", "apache-terms", "apache-end?"]),
    ("MIT", ["mit-release"]),
    ("MIT", ["mit-under"]),
    ("MIT", ["mit-title", "mit-grant", "mit-notice", "mit-asis?", "mit-liability?"]),
    ("MIT", ["mit-grant", "mit-notice", "mit-asis?", "mit-liability?"]),
    ("MIT", ["mit-title", "mit-grant-short", "mit-notice", "mit-asis?", "mit-liability?"]),
    ("MIT", ["mit-grant-short", "mit-notice", "mit-asis?", "mit-liability?"]),
    ("ISC", ["isc-under"]),
    ("ISC", ["isc-title", "isc-grant", "isc-asis?"]),
    ("ISC", ["isc-grant", "isc-asis?"]),
    ("0BSD", ["isc-grant-0", "isc-asis"]),
    ("BSD", ["bsd-under"]),
    ("BSD-{num}-Clause", ["bsd-under-num"]),
    ("BSD-2-Clause", ["bsd-title?", "bsd-grant", "bsd-source", "bsd-binary", "bsd-asis?", "bsd-liability?"]),
    ("BSD-3-Clause", ["bsd-title?", "bsd-grant", "bsd-source", "bsd-binary", "bsd-endorse", "bsd-asis?", "bsd-liability?"]),
    ("BSD-3-Clause", ["bsd-title?", "bsd-grant", "bsd-source", "bsd-binary", "bsd-endorse-names", "bsd-asis?", "bsd-liability?"]),
    ("BSD-3-Clause", ["bsd-title?", "bsd-grant", "bsd-source", "bsd-binary", "bsd-endorse-old", "bsd-asis?", "bsd-liability?"]),
    ("BSD-4-Clause", ["bsd-title?", "bsd-grant", "bsd-source", "bsd-binary", "bsd-advert", "bsd-endorse", "bsd-asis?", "bsd-liability?"]),
    ("BSD-4-Clause", ["bsd-title?", "bsd-grant", "bsd-source", "bsd-binary", "bsd-advert", "bsd-endorse-names", "bsd-asis?", "bsd-liability?"]),
    ("Zlib", ["zlib-asis", "zlib-liability", "zlib-grant", "zlib-origin?"]),
    ("BSL-{num}", ["boost-title", "boost-grant?"]),
    ("BSL-{num}", ["boost-under"]),
    ("CC-BY-NC-{num}", ["cc-nc"]),
    ("CC-BY-NC-SA-{num}", ["cc-nc-sa"]),
    ("CC-BY-NC-ND-{num}", ["cc-nc-nd"]),
    ("CC-BY-ND-{num}", ["cc-nd"]),
    ("CC-BY-SA-{num}", ["cc-sa"]),
    ("CC-BY-{num}", ["cc-by"]),
    ("CC-BY-{num}", ["cc-work"]),
    ("CC-BY-SA-{num}", ["cc-work-sa"]),
    ("CC-BY-NC-{num}", ["cc-work-nc"]),
    ("CC-BY-NC-SA-{num}", ["cc-work-nc-sa"]),
    ("CC0-{num}", ["cc-zero"]),
    ("CC0-{num}", ["cc-zero-under"]),
    ("CC0-{num}", ["cc-zero-title"]),
    ("MPL-{num}", ["mpl-grant", "mpl-copy?"]),
    ("MPL-{num}", ["mpl-title"]),
    ("MPL-{num}", ["mpl-under"]),
    ("EPL-{num}", ["epl-terms"]),
    ("EPL-{num}", ["epl-title"]),
    ("EPL-{num}", ["epl-under"]),
    ("Artistic-{num}", ["artistic-title"]),
    ("WTFPL", ["wtfpl-title"]),
    ("Unlicense", ["unlicense", "unlicense-anyone?"]),
    ("Public-Domain", ["public-domain"]),
    ("Proprietary", ["reserved"]),
]
for _id, (_name, _) in GNU.items():
    RULES += [
        (f"{_name}-{{num}}", [f"{_id}-under"]),
        (f"{_name}-{{num}}-or-later", [f"{_id}-under-later"]),
        (f"{_name}-{{num}}-or-later", ["free-software?", f"{_id}-terms", "either-later", "gpl-hope?"]),
        (f"{_name}-{{num}}-or-later", ["free-software?", f"{_id}-terms-later", "gpl-hope?"]),
        (f"{_name}-{{num}}", ["free-software?", f"{_id}-terms-num", "gpl-hope?"]),
        (f"{_name}-{{num}}", ["free-software?", f"{_id}-terms-of", "gpl-hope?"]),
        (_name, ["free-software?", f"{_id}-terms", "gpl-hope?"]),
        (f"{_name}-{{num}}", [f"{_id}-title", "verbatim?"]),
    ]
#: A license that yields to any other that comes after it.
LAST_RESORT = "Proprietary"
#: A text without any of these can't hold a known sentence that a rule begins with.
GATE = re.compile(r"licen[sc]e|rights\s+reserved|public\s+domain|permission|redistribut|provided|free\s+software|cc0", re.I)
WORD = re.compile(r"[A-Za-z]+[0-9]?(?![A-Za-z0-9])|[A-Za-z]+|[0-9]+(?:\.[0-9]+)*")
SPELLINGS = {"licence": "license", "licences": "licenses", "licenced": "licensed", "acknowledgment": "acknowledgement"}
STOP = re.compile(r"""[.;:!?]["')\]]*(?:\s|$)""")
EMPTY_LINE = re.compile(r"\n[^\w\n]*\n")
LIST_MARK = re.compile(r"(?:^|\n)[^\w\n]*\(?(?:[0-9]{1,2}|[A-Za-z]|[ivx]{1,4})[.)]\s")
TAG = re.compile(r"SPDX-License-Identifier:[ \t]*([A-Za-z0-9.+()\- \t]+)", re.I)
NAME = re.compile(r"[A-Za-z0-9.+\-]+")
SOFT, HARD = "\n", "\x1e"


def words_of(text: str) -> tuple[list[str], list[str], list[tuple[int, int]]]:
    """The words, the break before each (a blank for none) and their places in the text."""
    words, breaks, places, at, marked = [], [], [], 0, False
    for m in WORD.finditer(text):
        gap = text[at : m.start()]
        word = m[0].lower()
        if ("\n" in gap or not at) and len(word) < 5 and text[m.end() : m.end() + 1] in (".", ")") and LIST_MARK.match(text, max(0, at + gap.rfind("\n") if "\n" in gap else 0)):
            at, marked = m.end(), True
            continue
        if not words or marked or EMPTY_LINE.search(gap) or (STOP.match(gap.lstrip("\"')]")) and len(words[-1]) > 1):
            breaks.append(HARD)
        else:
            breaks.append(SOFT if "\n" in gap else " ")
        words.append(SPELLINGS.get(word, word))
        places.append((m.start(), m.end()))
        at, marked = m.end(), False
    return words, breaks, places


def pattern(sentence: str) -> re.Pattern:
    """A sentence of the table as a regular expression over words with their breaks before them."""
    parts, out = sentence.split(), r"(?<=[\n\x1e])"
    open_end = parts[-1] == "..."
    if open_end:
        parts.pop()
    if parts[0] == "...":
        parts.pop(0)
        out += r"(?:[^ \n\x1e]+ ){0,8}?"  # on one line: after a line's end the sentence could begin anew
    for i, p in enumerate(parts):
        gap = "" if i == len(parts) - 1 else r"[ \n]"
        if p == "...":
            out += r"(?:[^ \n\x1e]+[ \n]){0,40}?"
        elif p.endswith("?"):
            # the blank goes with the word; at the end the one before it does
            out = out.removesuffix(r"[ \n]") + rf"(?:[ \n](?:{p[:-1]}))?" if not gap else out + rf"(?:(?:{p[:-1]})[ \n])?"
        else:
            out += (r"(?P<num>[0-9.]+)" if p == "{num}" else f"(?:{p})") + gap
    if open_end:
        out += r"(?:[ \n][^ \n\x1e]+){0,60}?"
    return re.compile(out + r"(?=[\n\x1e])")


def rarest(sentence: str) -> str:
    """The longest word that every form of the sentence has."""
    return max((w for w in sentence.split() if w.isalnum()), key=lambda w: (len(w), w))


class RuleBook:
    def __init__(self, known: dict[str, str] = SENTENCES, rules=RULES, gap: int = 1):
        self.gap = gap
        self.known = [(name, pattern(s), rarest(s)) for name, s in known.items()]
        self.starts: dict[str, list] = {}
        for place, (name, wanted) in enumerate(rules):
            # a rule may begin with its second sentence where the first may be missing
            for i, w in enumerate(wanted):
                self.starts.setdefault(w.rstrip("?"), []).append((place, name, wanted[i:]))
                if not w.endswith("?"):
                    break

    def identify(self, words: list[str], breaks: list[str]) -> list[tuple[int, int, str, str | None]]:
        """(first word, word after the last, identifier, number) of the known sentences, in order and without overlap."""
        stream = "".join(b + w for b, w in zip(breaks, words)) + HARD
        starts, at, have = [], 0, set(words)
        for w in words:
            starts.append(at + 1)
            at += 1 + len(w)
        found = []
        for order, (name, rx, mark) in enumerate(self.known):
            if mark in have:
                for m in rx.finditer(stream):
                    if m.end() > m.start():
                        found.append((bisect_left(starts, m.start()), -bisect_left(starts, m.end()), order, name, m.groupdict().get("num")))
        out, end = [], 0
        for first, last, _, name, num in sorted(found, key=lambda f: f[:3]):
            if first >= end:
                out.append((first, end := -last, name, num))
        return out

    def follow(self, row: list, i: int, wanted: list[str]) -> tuple[int, int, str | None] | None:
        """(last place, number of sentences, number) where the rule fits from place i on."""
        at, n, num = i, 1, row[i][3]
        for w in wanted[1:]:
            near = (k for k in range(at + 1, min(len(row), at + 2 + self.gap)) if row[k][2] == w.rstrip("?") and row[k][0] - row[at][1] <= WORDS_BETWEEN)
            k = next(near, None)
            if k is not None:
                at, n, num = k, n + 1, num or row[k][3]
            elif not w.endswith("?"):
                return None
        return at, n, num

    def find(self, text: str | None) -> list[tuple[int, int, str]]:
        """(start, end, license) of the licenses in a text, in order of start; places count code points."""
        if not text or not GATE.search(text):
            return []
        words, breaks, places = words_of(text)
        row, out, i = self.identify(words, breaks), [], 0
        while i < len(row):
            fits = [(-f[1], place, f, name) for place, name, wanted in self.starts.get(row[i][2], ()) if (f := self.follow(row, i, wanted))]
            if not fits:
                i += 1
                continue
            _, _, (last, _, num), name = min(fits, key=lambda x: x[:2])
            out.append((places[row[i][0]][0], places[row[last][1] - 1][1], named(name, num)))
            i = last + 1
        out = sorted(out + tagged(text))
        return [x for i, x in enumerate(out) if x[2] != LAST_RESORT or not any(y[2] != LAST_RESORT for y in out[i + 1 :])]


def named(name: str, num: str | None) -> str:
    num = (num or "").strip(".")
    if "GPL-" in name and num and "." not in num:
        num += ".0"
    return name.replace("{num}", num).rstrip("-")


def tagged(text: str) -> list[tuple[int, int, str]]:
    """(start, end, license) of each license named in an expression after the tag; what follows WITH is an exception, not a license."""
    out = []
    for m in TAG.finditer(text):
        skip = False
        for n in NAME.finditer(m[1]):
            if n[0].upper() in ("OR", "AND", "WITH"):
                skip = n[0].upper() == "WITH"
                continue
            if not skip and (n[0][0].isalnum()):
                out.append((m.start(1) + n.start(), m.start(1) + n.end(), n[0].rstrip(".-")))
            skip = True  # a name is followed by an operator; other words are no names
    return out


@lru_cache(1)
def rule_book() -> RuleBook:
    return RuleBook()


def license_scan(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """One row per input row: doc_id, n_licenses, licenses (distinct names, sorted, joined by commas), spans (license:start:end in code points, in order).

    Null and empty texts have none. Null ids and repeated rows count like others; other columns aren't read; an empty table gives an empty result.
    """
    ship_package(docs.sparkSession)

    @F.pandas_udf("n_licenses long, licenses string, spans string")
    def scan(texts: pd.Series) -> pd.DataFrame:
        find, rows = rule_book().find, []
        for t in texts:
            found = find(t)
            rows.append((len(found), ",".join(sorted({n for _, _, n in found})), ",".join(f"{n}:{a}:{b}" for a, b, n in found)))
        return pd.DataFrame(rows, columns=["n_licenses", "licenses", "spans"])

    return docs.select(F.col(id_col).alias("doc_id"), scan(F.col(text_col).cast("string")).alias("s")).select("doc_id", "s.*")
