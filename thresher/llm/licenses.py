"""License scans by ordered signature rules, with DataFrame functions only.

Rules are regular expressions over normalised words (A-Z lower-cased, one blank between words and
around the text), each with a keyword, a label, a priority and a confidence. A text that holds no
keyword at all runs no rule; of the others each rule runs only on texts with its own keyword.
Detections are intervals of words. One that lies inside the interval of a detection of higher
priority is suppressed, and so is the lesser of two on one interval; what overlaps in part stays.

The base phrases are looked for in every text; their places and labels are reported whatever is suppressed.

Defined cases: null and empty texts have no words, no detections and empty labels; repeated
rows are scanned each; very long texts are scanned whole, their detections are ordered per
row; an empty table gives no rows; further columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import LOWER, UPPER, SharedTable, prepare

#: Phrases and labels that every scan reports.
BASE = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}
_NOT_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Normalised texts hold no control characters.
_MARK = "\x01"
#: Texts that one task runs rules on.
TEXTS = 2000


@dataclass(frozen=True)
class Rule:
    keyword: str
    pattern: str
    label: str
    priority: int
    confidence: float


#: License families as (label, names, short identifiers, versions).
FAMILIES = [
    ("gpl", ["gnu general public license", "gnu gpl"], ["gpl"], ["1", "2", "3"]),
    ("lgpl", ["gnu lesser general public license", "gnu library general public license", "gnu lgpl"], ["lgpl"], ["2", "2 1", "3"]),
    ("agpl", ["gnu affero general public license", "affero general public license"], ["agpl"], ["1", "3"]),
    ("gfdl", ["gnu free documentation license"], ["gfdl"], ["1 1", "1 2", "1 3"]),
    ("apache", ["apache license", "apache software license"], ["apache"], ["1 0", "1 1", "2 0"]),
    ("mit", ["mit license", "expat license"], ["mit"], []),
    ("bsd", ["bsd license", "berkeley software distribution license"], ["bsd"], ["2 clause", "3 clause", "4 clause"]),
    ("mpl", ["mozilla public license"], ["mpl"], ["1 0", "1 1", "2 0"]),
    ("epl", ["eclipse public license"], ["epl"], ["1 0", "2 0"]),
    ("cddl", ["common development and distribution license"], ["cddl"], ["1 0", "1 1"]),
    ("cpl", ["common public license"], ["cpl"], ["1 0"]),
    ("artistic", ["artistic license"], ["artistic"], ["1 0", "2 0"]),
    ("isc", ["isc license", "internet systems consortium license"], ["isc"], []),
    ("zlib", ["zlib license", "zlib libpng license"], ["zlib"], []),
    ("boost", ["boost software license"], ["bsl"], ["1 0"]),
    ("unlicense", ["the unlicense"], ["unlicense"], []),
    ("wtfpl", ["do what the fuck you want to public license"], ["wtfpl"], ["2"]),
    ("eupl", ["european union public licence", "european union public license"], ["eupl"], ["1 1", "1 2"]),
    ("osl", ["open software license"], ["osl"], ["1 0", "2 0", "3 0"]),
    ("afl", ["academic free license"], ["afl"], ["2 1", "3 0"]),
    ("postgresql", ["postgresql license"], ["postgresql"], []),
    ("python", ["python software foundation license", "psf license"], ["psf"], ["2"]),
    ("php", ["php license"], ["php"], ["3 0", "3 01"]),
    ("openssl", ["openssl license"], ["openssl"], []),
    ("ofl", ["sil open font license", "open font license"], ["ofl"], ["1 0", "1 1"]),
    ("odbl", ["open database license"], ["odbl"], ["1 0"]),
    ("cc0", ["cc0 public domain dedication", "creative commons zero"], ["cc0"], ["1 0"]),
    ("cc-by", ["creative commons attribution license"], ["cc by"], ["2 0", "2 5", "3 0", "4 0"]),
    ("cc-by-sa", ["creative commons attribution sharealike license", "creative commons attribution share alike license"], ["cc by sa"], ["2 0", "2 5", "3 0", "4 0"]),
    ("cc-by-nc", ["creative commons attribution noncommercial license", "creative commons attribution non commercial license"], ["cc by nc"], ["2 0", "2 5", "3 0", "4 0"]),
    ("cc-by-nd", ["creative commons attribution noderivatives license", "creative commons attribution no derivatives license"], ["cc by nd"], ["2 0", "2 5", "3 0", "4 0"]),
    ("cc-by-nc-sa", ["creative commons attribution noncommercial sharealike license"], ["cc by nc sa"], ["2 0", "2 5", "3 0", "4 0"]),
    ("cc-by-nc-nd", ["creative commons attribution noncommercial noderivatives license"], ["cc by nc nd"], ["2 0", "2 5", "3 0", "4 0"]),
    ("ms-pl", ["microsoft public license"], ["ms pl"], []),
    ("ms-rl", ["microsoft reciprocal license"], ["ms rl"], []),
    ("sspl", ["server side public license"], ["sspl"], ["1"]),
    ("busl", ["business source license"], ["busl"], ["1 1"]),
    ("elastic", ["elastic license"], ["elastic"], ["2 0"]),
]
#: Passages of license texts, headers and notices, each as its label and its expression over normalised words.
PASSAGES = r"""
mit|permission is hereby granted free of charge to any person obtaining a copy
mit|to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies
mit|the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software
mit|the software is provided as is without warranty of any kind express or implied
mit|in no event shall the authors or copyright holders be liable for any claim damages or other liability
mit|(?:see|refer to) the (?:file )?license(?: md| txt)? (?:file )?for the mit license
x11|except as contained in this notice the name of (?:\S+ ){1,8}shall not be used in advertising
mit-0|to permit persons to whom the software is furnished to do so the software is provided as is
json|the software shall be used for good not evil
bsd|redistribution and use in source and binary forms with or without modification are permitted
bsd|redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer
bsd|redistributions in binary form must reproduce the above copyright notice this list of conditions
bsd|neither the name of (?:\S+ ){1,12}nor the names of its contributors
bsd|all advertising materials mentioning features or use of this software must display the following acknowledge?ment
bsd|this software is provided by the (?:copyright holders and contributors|regents and contributors|author) as is and any express(?:ed)? or implied warranties
bsd|use of this source code is governed by a bsd style license
bsd|licensed under the (?:new|revised|modified|simplified) bsd license
bsd|the (?:regents of the university of california|university of california berkeley) and its contributors
0bsd|permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted the software
isc|permission to use copy modify and (?:or )?distribute this software for any purpose with or without fee is hereby granted provided that
isc|the software is provided as is and the author disclaims all warranties with regard to this software
hpnd|permission to use copy modify and distribute this software and its documentation for any purpose and without fee is hereby granted
hpnd|not be used in advertising or publicity pertaining to distribution of the software without specific written prior permission
ncsa|redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimers
ncsa|university of illinois ncsa open source license
zlib|altered source versions must be plainly marked as such and must not be misrepresented as being the original software
zlib|this software is provided as is without any express or implied warranty in no event will the authors be held liable
zlib|the origin of this software must not be misrepresented you must not claim that you wrote the original software
zlib|this notice may not be removed or altered from any source distribution
libpng|this copyright notice may not be removed or altered from any source or altered source distribution
libpng|the contributing authors and group 42 inc disclaim all warranties
boost|permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation
boost|unless such copies or derivative works are solely in the form of machine executable object code
boost|distributed under the boost software license version 1 0
apache|licensed under the apache license version 2 0 the license
apache|you may not use this file except in compliance with the license
apache|you may obtain a copy of the license at http(?:s)? www apache org licenses license 2 0
apache|unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis
apache|see the license for the specific language governing permissions and limitations under the license
apache|licensed to the apache software foundation asf under one or more contributor license agreements
apache|this product includes software developed by the apache (?:software foundation|group)
apache|terms and conditions for use reproduction and distribution
apache|subject to the terms and conditions of this license each contributor hereby grants to you a perpetual worldwide non exclusive no charge royalty free irrevocable (?:copyright|patent|except)
apache|the names? apache(?: server)?(?: and)? (?:\S+ ){0,6}must not be used to endorse or promote products
gpl|is free software you can redistribute it and or modify it under the terms of the gnu general public license
gpl|either version [23] of the license or at your option any later version
gpl|you should have received a copy of the gnu general public license along with
gpl|this program is distributed in the hope that it will be useful but without any warranty
gpl|without even the implied warranty of merchantability or fitness for a particular purpose
gpl|write to the free software foundation inc
gpl|everyone is permitted to copy and distribute verbatim copies of this license document but changing it is not allowed
gpl|the licenses for most software are designed to take away your freedom to share and change it
gpl|the gnu general public license is a free copyleft license for software and other kinds of works
gpl|this program comes with absolutely no warranty
gpl|the work must carry prominent notices stating that you modified it
gpl|as a special exception the copyright holders (?:of this library )?give you permission to link
gpl|released under gnu gpl(?: v| version)? ?[23]
gpl|dual licensed under (?:the )?(?:mit|bsd) (?:and|or) gpl
lgpl|under the terms of the gnu (?:lesser|library) general public license as published by the free software foundation
lgpl|you should have received a copy of the gnu (?:lesser|library) general public license
lgpl|a program that contains no derivative of any portion of the library but is designed to work with the library
lgpl|the lesser general public license permits more lax criteria for linking other code with the library
lgpl|license is called the lesser general public license because it does less to protect the user s freedom
agpl|under the terms of the gnu affero general public license as published by the free software foundation
agpl|you should have received a copy of the gnu affero general public license
agpl|remote network interaction use with the gnu general public license
agpl|your modified version must prominently offer all users interacting with it remotely through a computer network
gfdl|permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation license
gfdl|with no invariant sections no front cover texts and no back cover texts
gfdl|with the invariant sections being list their titles
fsf-permissive|copying and distribution of this file with or without modification are permitted in any medium without royalty
fsf-permissive|this file is free software the free software foundation gives unlimited permission to copy and or distribute it
mpl|this source code form is subject to the terms of the mozilla public license v 2 0
mpl|if a copy of the mpl was not distributed with this file you can obtain one at
mpl|the contents of this file are subject to the mozilla public license version 1 [01]
mpl|software distributed under the license is distributed on an as is basis without warranty of any kind either express or implied
mpl|alternatively the contents of this file may be used under the terms of either the gnu general public license
mpl|this source code form is incompatible with secondary licenses
npl|the contents of this file are subject to the netscape public license
epl|this program and the accompanying materials are made available under the terms of the eclipse public license
epl|the accompanying program is provided under the terms of this eclipse public license agreement
epl|any use reproduction or distribution of the program constitutes recipient s acceptance of this agreement
epl|this source code may also be made available under the following secondary licenses
edl|available under the terms of the eclipse distribution license
cpl|the accompanying program is provided under the terms of this common public license
ipl|the accompanying program is provided under the terms of this ibm public license
cddl|the contents of this file are subject to the terms of the common development and distribution license
cddl|when distributing covered code include this cddl header in each file
cddl|you can obtain a copy of the license at (?:usr src opensolaris license|http www opensolaris org os licensing)
cddl|and or its subsidiaries all rights reserved use is subject to license terms
artistic|the intent of this document is to state the conditions under which a package may be copied
artistic|this license establishes the terms under which a given free software package may be copied modified distributed and or redistributed
artistic|you can redistribute it and or modify it under the same terms as perl itself
artistic|you may distribute verbatim copies of the standard version
ruby|you can redistribute it and or modify it under either the terms of the 2 clause bsdl
ruby|ruby is copyrighted free software by yukihiro matsumoto
php|this source file is subject to version 3 01? ?[01]? of the php license
php|the name php must not be used to endorse or promote products derived from this software
php|this product includes php software freely available from
python|python software foundation license version 2
python|psf hereby grants licensee a nonexclusive royalty free world wide license
python|permission to use copy modify and distribute this software and its documentation for any purpose and without fee is hereby granted provided that the above copyright notice appear in all copies .{0,20}stichting mathematisch centrum
python|licensee agrees to be bound by the terms and conditions of this license agreement
openssl|this product includes software developed by the openssl project for use in the openssl toolkit
openssl|the names openssl toolkit and openssl project must not be used
ssleay|this package is an ssl implementation written by eric young
postgresql|in no event shall the university of california be liable to any party for direct indirect special incidental or consequential damages
postgresql|permission to use copy modify and distribute this software and its documentation for any purpose without fee and without a written agreement
sleepycat|redistributions in any form must be accompanied by information on how to obtain complete source code
unlicense|this is free and unencumbered software released into the public domain
unlicense|anyone is free to copy modify publish use compile sell or distribute this software
unlicense|for more information please refer to http(?:s)? unlicense org
wtfpl|you just do what the fuck you want to
wtfpl|do what the fuck you want to public license
beerware|as long as you retain this notice you can do whatever you want with this stuff
beerware|if we meet some day and you think this stuff is worth it you can buy me a beer
cc0|to the extent possible under law (?:\S+ ){1,12}waived all copyright and related or neighboring rights
cc0|no copyright the person who associated a work with this deed has dedicated the work to the public domain
cc-by|this work is licensed under a creative commons attribution (?:[0-9] [0-9] )?(?:international|unported|generic)
cc-by|creativecommons org licenses by [1-4] [05]
cc-by|you must give appropriate credit provide a link to the license and indicate if changes were made
cc-by|content is available under cc by
cc-by-sa|this work is licensed under a creative commons attribution sharealike
cc-by-sa|creativecommons org licenses by sa [1-4] [05]
cc-by-sa|if you remix transform or build upon the material you must distribute your contributions under the same license as the original
cc-by-sa|text is available under the creative commons attribution share ?alike license
cc-by-nc|this work is licensed under a creative commons attribution non ?commercial
cc-by-nc|creativecommons org licenses by nc [1-4] [05]
cc-by-nc|you may not use the material for commercial purposes
cc-by-nd|if you remix transform or build upon the material you may not distribute the modified material
cc-by-nd|creativecommons org licenses by nd [1-4] [05]
cc-by-nc-sa|creativecommons org licenses by nc sa [1-4] [05]
cc-by-nc-nd|creativecommons org licenses by nc nd [1-4] [05]
odbl|this (?:\S+ ){0,3}database is made available under the open database license
odbl|any rights in individual contents of the database are licensed under the database contents license
pddl|open data commons public domain dedication and licen[cs]e
odc-by|open data commons attribution license
ogl|contains public sector information licensed under the open government licen[cs]e
etalab|licence ouverte open licence
ofl|this font software is licensed under the sil open font license
ofl|the font software may be sold as part of a larger software package but no copy of one or more of the font software typefaces
ofl|with reserved font name
bitstream-vera|all copyright and trademark notices must be retained .{0,40}bitstream vera
ms-pl|if you use the software you accept this license if you do not accept the license do not use the software
ms-pl|each contributor grants you a non exclusive worldwide royalty free copyright license to reproduce its contribution
ms-rl|for any file you distribute that contains code from the software in source code or binary format you must provide recipients the source code
eupl|licensed under the eupl(?: version)?(?: 1 [012])?
eupl|licence for the european union public licence
osl|licensed under the open software license version (?:1 0|2 0|2 1|3 0)
afl|licensed under the academic free license version (?:1 2|2 0|2 1|3 0)
ecl|licensed under the educational community license version 2 0
upl|the universal permissive license upl version 1 0
lppl|this work may be distributed and or modified under the conditions of the latex project public license
lppl|this work has the lppl maintenance status
cecill|this software is governed by the cecill(?: b| c)? license under french law
mulan|you can use this software according to the terms and conditions of the mulan psl v2
blueoak|blue oak model license
vim|vim is charityware you can use and copy it as much as you like
curl|curl and libcurl are licensed under a license derived from mit x
ijg|this software is based in part on the work of the independent jpeg group
freetype|portions of this software are copyright (?:\S+ ){1,4}the freetype project
icu|icu license icu 1 8 1 and later
unicode|unicode inc license agreement data files and software
unicode|distributed under the terms of use in http(?:s)? www unicode org copyright html
w3c|this work is being provided by the copyright holders under the following license .{0,30}w3c
w3c|w3c software (?:and document )?notice and license
zpl|zope public license zpl version 2 [01]
tcl|the authors hereby grant permission to use copy modify distribute and license this software and its documentation for any purpose
info-zip|this is version (?:\S+ ){1,6}of the info zip license
qpl|the q public license version 1 0
sspl|server side public license version 1
sspl|if you make the functionality of the program or a modified version available to third parties as a service
busl|business source license 1 1
busl|the licensor hereby grants you the right to copy modify create derivative works redistribute and make non production use of the licensed work
busl|change date (?:\S+ ){0,6}change license
elastic|you may not provide the software to third parties as a hosted or managed service
commons-clause|the license does not grant to you the right to sell the software
polyform|polyform (?:noncommercial|small business|shield|perimeter|strict) license
openrail|responsible ai license
openrail|use restrictions as referenced in paragraph 5 cannot be considered comprehensive
llama|llama [23](?: [0-9])? community license agreement
public-domain|(?:dedicated to|placed in|released into|donated to) the public domain
public-domain|this (?:file|code|software|work) is in the public domain
public-domain|no copyright is claimed in the united states under title 17
us-government|this software was developed (?:at|by) (?:\S+ ){1,12}employees? of the federal government
proprietary|all rights reserved
proprietary|proprietary and confidential
proprietary|unauthorized copying of this file via any medium is strictly prohibited
proprietary|no part of this publication may be reproduced
proprietary|this is a licensed product and not sold
proprietary|for internal use only
proprietary|end user license agreement
trademark|is a trademark of
trademark|is a registered trademark of
copyright|copyright (?:c )?(?:19|20)[0-9]{2}(?: (?:19|20)[0-9]{2})?
copyright|copyright (?:c )?[^ ]+ (?:19|20)[0-9]{2}
"""
_LINES = [
    ("licensed under {x}", 2, 0.95),
    ("released under {x}", 2, 0.95),
    ("distributed under {x}", 2, 0.95),
    ("available under {x}", 2, 0.9),
    ("under the terms of {x}", 2, 0.95),
    ("governed by {x}", 2, 0.85),
    ("subject to {x}", 2, 0.85),
]


def longest_phrase(pattern: str) -> str:
    """The longest run of plain words that every match of an expression holds: what the gate looks for."""
    runs, run, depth = [], [], 0
    for word in pattern.split(" "):
        plain = depth == 0 and word.isalnum()
        depth += word.count("(") - word.count(")")
        run = [*run, word] if plain else []
        runs.append(run)
    return " ".join(max(runs, key=lambda r: len(" ".join(r))))


def rules() -> list[Rule]:
    """All rules: for each family its notices, names with version, bare names and identifiers."""
    found = []
    for line in PASSAGES.strip().splitlines():
        label, pattern = line.split("|", 1)
        found.append(Rule(longest_phrase(pattern), f" {pattern}(?= )", label, 1, 0.9))
    for label, names, short, versions in FAMILIES:
        version = "(?:" + "|".join(sorted(versions, key=len, reverse=True)) + ")" if versions else None
        tail = f"(?: (?:version|v))? v?{version}(?: (?:or any later version|or later|only))?" if version else ""
        for name in names:
            for form, priority, confidence in _LINES:
                x = f"(?:the |a )?{name}" + (f"(?:{tail})?" if tail else "")
                found.append(Rule(name, f" (?:this \\S+ is )?{form.format(x=x)}(?= )", label, priority, confidence))
            if tail:
                found.append(Rule(name, f" (?:the )?{name}{tail}(?= )", label, 3, 0.9))
            found.append(Rule(name, f" {name}(?= )", label, 4, 0.8))
        for s in short:
            found.append(Rule(f"identifier {s}", f" spdx license identifier {s}(?: {version})?(?: (?:or later|only))?(?= )" if version else f" spdx license identifier {s}(?= )", label, 0, 1.0))
            # Words that are a language's own need the word license or a version beside them.
            beside = f"(?: {version}| license)" if version else "(?: license| licensed)"
            found.append(Rule(s, f" {s}{beside}(?= )", label, 3, 0.85))
            found.append(Rule(s, f" (?:license|licence|licensed under|released under|under) (?:the )?{s}(?: {version})?(?= )" if version else f" (?:license|licence|licensed under|released under|under) (?:the )?{s}(?= )", label, 3, 0.85))
            if " " in s:
                found.append(Rule(s, f" {s}(?= )", label, 4, 0.7))
    return found


def normalised(text: Column) -> Column:
    """Words with single blanks between and around them."""
    plain = F.regexp_replace(F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER), _NOT_WORD, " ")
    return F.concat(F.lit(" "), F.trim(plain), F.lit(" "))


def _spans(norm: Column, pattern: Column) -> Column:
    """Word intervals [first, last] of a pattern's places, in one walk. Patterns begin with the blank before a word.

    Every place is marked at the end of the word before it: the marks' places in the list of words are the starts.
    """
    found = F.regexp_extract_all(norm, pattern, F.lit(0))
    pieces = F.split(F.regexp_replace(norm, pattern, F.lit(_MARK + "$0")), " ")
    starts = F.filter(F.transform(pieces, lambda w, k: F.when(F.endswith(w, F.lit(_MARK)), k)), lambda k: k.isNotNull())
    # A match holds a blank for each of its words.
    words = lambda x: F.length(x) - F.length(F.replace(x, F.lit(" "), F.lit("")))
    return F.zip_with(starts, found, lambda first, hit: F.struct(first.alias("first"), (first + words(hit) - 1).alias("last")))


def anchor(keyword: str) -> str:
    """The word without which a keyword can't stand in a text: ``license``, or its longest."""
    words = keyword.split(" ")
    return "license" if "license" in words else max(words, key=len)


def anchors_in(signature: list[Rule]) -> Column:
    """The anchors that a text holds: one look at each word, whatever the number of rules."""
    every = sorted({anchor(r.keyword) for r in signature})
    return F.array_intersect(F.split("norm", " "), F.array(*map(F.lit, every)))


def gate(signature: list[Rule]) -> Column:
    """Whether a text has an anchor at all."""
    return F.size(anchors_in(signature)) > 0


def detections(docs: DataFrame, signature: list[Rule] | None = None) -> DataFrame:
    """row, label, priority, confidence, first and last word of what stands after suppression.

    ``docs`` has the columns ``row`` (unique) and ``norm``.
    """
    signature = rules() if signature is None else signature
    spark = docs.sparkSession
    number = {k: n for n, k in enumerate(sorted({r.keyword for r in signature}))}
    # Rules and keywords are fixed lists. A text meets the keywords of its anchors only.
    keys = spark.createDataFrame([(anchor(k), f" {k} ", n) for k, n in number.items()], "anchor string, keyword string, n int")
    met = docs.select("row", "norm", F.explode(anchors_in(signature)).alias("anchor")).join(F.broadcast(keys), "anchor")
    passed = met.where(F.contains("norm", F.col("keyword"))).select("row", "norm", "n")
    listed = spark.createDataFrame([(number[r.keyword], r.pattern, r.label, r.priority, r.confidence) for r in signature], "n int, pattern string, label string, priority int, confidence double")
    # Few texts pass, but each costs much: they are dealt out evenly, whatever files they came from.
    passed = passed.repartition(max(spark.sparkContext.defaultParallelism, -(-docs.count() // TEXTS)), "row", "n")
    # The rules are a fixed list.
    run = passed.join(F.broadcast(listed), "n").withColumn("span", F.explode(_spans(F.col("norm"), F.col("pattern"))))
    found = run.select("row", "label", "priority", "confidence", F.col("span.first").alias("first"), F.col("span.last").alias("last")).distinct()
    order = Window.partitionBy("row").orderBy("first", F.desc("last"), "priority", F.desc("confidence"), "label").rowsBetween(Window.unboundedPreceding, -1)
    levels = sorted({r.priority for r in signature})
    # The furthest end so far of each priority: an interval that begins later and ends before it lies inside.
    reach = [F.max(F.when(F.col("priority") == p, F.col("last"))).over(order).alias(f"reach_{p}") for p in levels]
    seen = found.select("*", *reach)
    inside = F.lit(False)
    for p in levels:
        inside = inside | ((F.col("priority") > p) & F.coalesce(F.col(f"reach_{p}") >= F.col("last"), F.lit(False)))
    twin = Window.partitionBy("row", "first", "last").orderBy("priority", F.desc("confidence"), "label")
    kept = seen.where(~inside).withColumn("nth", F.row_number().over(twin)).where("nth = 1")
    return kept.select("row", "label", "priority", "confidence", "first", "last")


def base_places(norm: Column) -> Column:
    """(first, label) of every place of a base phrase."""

    def places(phrase: str, label: str) -> Column:
        return F.transform(_spans(norm, F.lit(f" {phrase}(?= )")), lambda s: F.struct(s["first"].alias("first"), F.lit(label).alias("label")))

    return F.concat(*[places(phrase, label) for phrase, label in BASE.items()])


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, n_detections."""
    prepare(docs.sparkSession)
    signature = rules() + [Rule(phrase, "", label, 0, 0.0) for phrase, label in BASE.items()]
    norm = docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", normalised(F.col("text")).alias("norm"))
    n_words = F.when(F.col("norm") == "  ", 0).otherwise(F.length("norm") - F.length(F.replace("norm", F.lit(" "), F.lit(""))) - 1)
    none = F.array().cast("array<struct<first:int,label:string>>")
    # Stored once: the texts that go on to the rules are few, and the row numbers must not change.
    stored = SharedTable(norm.select("row", "doc_id", n_words.cast("long").alias("n_words"), F.when(gate(signature), F.col("norm")).alias("norm")), "licenses").read()
    passed = stored.where("norm is not null")
    found = detections(passed).groupBy("row").agg(F.collect_set("label").alias("own"), F.max("confidence").alias("sure"), F.count("*").alias("n_detections"))
    based = passed.select("row", F.when(F.rlike("norm", F.lit(" (?:license|cc by) ")), base_places(F.col("norm"))).otherwise(none).alias("base"))
    merged = stored.drop("norm").join(based.join(found, "row", "left").where("n_detections > 0 or size(base) > 0"), "row", "left")
    base = F.coalesce("base", none)
    labels = F.array_distinct(F.transform(base, lambda b: b["label"]))
    first = F.transform(base, lambda b: b["first"])
    own = F.coalesce("own", F.array().cast("array<string>"))
    join = lambda x: F.array_join(F.array_sort(x), ",")
    sure = F.greatest(F.coalesce("sure", F.lit(0.0)), F.when(F.size(base) > 0, 0.8).otherwise(0.0))
    return merged.select(
        "doc_id",
        "n_words",
        F.size(base).cast("long").alias("n_base"),
        F.array_min(first).cast("long").alias("first_word"),
        F.array_max(first).cast("long").alias("last_word"),
        join(labels).alias("base_labels"),
        join(F.array_union(labels, own)).alias("labels"),
        sure.alias("score"),
        F.coalesce("n_detections", F.lit(0)).alias("n_detections"),
    )

