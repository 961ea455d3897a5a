"""License scans by ordered signature rules, with DataFrame functions only.

Rules are names of license families in several forms, and sentences of the licenses themselves.  Texts are brought to lower-case words with one space between; a gate picks the texts and then keywords
the rules that are tried at all.  Keywords are worked out from the patterns: every match holds one.  Every match is an interval with its rule's priority; one
that lies inside an interval of higher priority, or a longer one of equal priority, is suppressed.
"""
from __future__ import annotations

from dataclasses import dataclass
from re._constants import BRANCH, LITERAL, MAX_REPEAT, SUBPATTERN
from re._parser import parse

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from provgraph.functions.columns import column, free_name

#: The phrases that always count, and their labels.
BASE = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}

#: Families as (label, identifier pattern, name pattern).
FAMILIES = [
    ("mit", r"mit(?: 0)?", r"mit(?: expat| x11| style)?"),
    ("expat", r"expat", r"expat"),
    ("x11", r"x11", r"x11"),
    ("isc", r"isc", r"isc|internet systems consortium"),
    ("apache-1.1", r"apache 1 1", r"apache(?: software)? licen[cs]e(?: version| v)? 1 1"),
    ("apache-2.0", r"apache 2 0", r"apache(?: licen[cs]e)?(?: version| v)? ?2(?: 0)?|asl ?2(?: 0)?"),
    ("apache", r"apache", r"apache(?: software)?"),
    ("gpl-1.0", r"gpl 1 0(?: only| or later)?", r"(?:gnu )?(?:gpl|general public licen[cs]e) ?(?:version |v)?1(?: 0)?"),
    ("gpl-2.0", r"gpl 2 0(?: only| or later)?", r"(?:gnu )?(?:gpl|general public licen[cs]e) ?(?:version |v)?2(?: 0)?"),
    ("gpl-3.0", r"gpl 3 0(?: only| or later)?", r"(?:gnu )?(?:gpl|general public licen[cs]e) ?(?:version |v)?3(?: 0)?"),
    ("gpl", r"gpl", r"(?:gnu )?gpl"),
    ("gpl", r"gpl", r"(?:gnu )?general public"),
    ("lgpl-2.0", r"lgpl 2 0(?: only| or later)?", r"(?:gnu )?(?:lgpl|(?:library|lesser) general public licen[cs]e) ?(?:version |v)?2(?: 0)?"),
    ("lgpl-2.1", r"lgpl 2 1(?: only| or later)?", r"(?:gnu )?(?:lgpl|lesser general public licen[cs]e) ?(?:version |v)?2 1"),
    ("lgpl-3.0", r"lgpl 3 0(?: only| or later)?", r"(?:gnu )?(?:lgpl|lesser general public licen[cs]e) ?(?:version |v)?3(?: 0)?"),
    ("lgpl", r"lgpl", r"(?:gnu )?lgpl"),
    ("lgpl", r"lgpl", r"(?:gnu )?lesser general public"),
    ("agpl-3.0", r"agpl 3 0(?: only| or later)?", r"(?:gnu )?affero general public licen[cs]e ?(?:version |v)?3(?: 0)?"),
    ("agpl", r"agpl(?: 3 0)?", r"(?:gnu )?agpl(?: ?v?3)?"),
    ("fdl", r"gfdl 1 [123]", r"(?:gnu )?free documentation"),
    ("bsd-0-clause", r"0bsd", r"(?:zero|0) clause bsd|bsd (?:zero|0) clause"),
    ("bsd-1-clause", r"bsd 1 clause", r"(?:one|1) clause bsd"),
    ("bsd-2-clause", r"bsd 2 clause(?: patent)?", r"(?:two|2) clause bsd|bsd (?:two|2) clause|simplified bsd|freebsd"),
    ("bsd-3-clause", r"bsd 3 clause(?: clear| lbnl)?", r"(?:three|3) clause bsd|bsd (?:three|3) clause|(?:new|modified|revised) bsd"),
    ("bsd-4-clause", r"bsd 4 clause(?: uc)?", r"(?:four|4) clause bsd|bsd (?:four|4) clause|original bsd"),
    ("bsd", r"bsd", r"bsd(?: style)?|berkeley software distribution"),
    ("mpl-1.1", r"mpl 1 1", r"mozilla public licen[cs]e ?(?:version |v)?1 [01]"),
    ("mpl-2.0", r"mpl 2 0", r"mozilla public licen[cs]e ?(?:version |v)?2(?: 0)?"),
    ("mpl", r"mpl 2 0", r"mpl(?: ?v?2(?: 0)?)?"),
    ("mpl", r"mpl", r"mozilla public"),
    ("epl-1.0", r"epl 1 0", r"eclipse public licen[cs]e ?(?:version |v)?1(?: 0)?"),
    ("epl-2.0", r"epl 2 0", r"eclipse public licen[cs]e ?(?:version |v)?2(?: 0)?"),
    ("epl", r"epl", r"eclipse public"),
    ("edl", r"edl 1 0", r"eclipse distribution"),
    ("cddl", r"cddl 1 [01]", r"cddl"),
    ("cddl", r"cddl", r"common development and distribution"),
    ("cpl", r"cpl 1 0", r"common public"),
    ("eupl", r"eupl 1 [012]", r"european union public"),
    ("eupl", r"eupl 1 [012]", r"eupl"),
    ("artistic", r"artistic [12] 0", r"(?:clarified )?artistic(?: licen[cs]e ?[12](?: 0)?)?"),
    ("perl", r"artistic 1 0 perl", r"(?:same terms as )perl(?: itself)?"),
    ("python", r"python 2 0(?: 1)?", r"python software foundation"),
    ("psf", r"psf 2 0", r"psf"),
    ("php", r"php 3 0(?:1)?", r"php"),
    ("ruby", r"ruby", r"ruby"),
    ("zlib", r"zlib(?: acknowledgement)?", r"zlib(?: libpng)?"),
    ("libpng", r"libpng(?: 2 0)?", r"libpng"),
    ("boost", r"bsl 1 0", r"boost software"),
    ("unlicense", r"unlicense", r"(?:the )?unlicense"),
    ("wtfpl", r"wtfpl", r"wtfpl"),
    ("public-domain", r"public domain", r"public domain"),
    ("cc0", r"cc0 1 0", r"cc0(?: 1 0)?"),
    ("cc-by", r"cc by [1234] 0", r"creative commons attribution(?: [1234] 0)?"),
    ("cc-by-sa", r"cc by sa [1234] 0", r"creative commons attribution share ?alike(?: [1234] 0)?"),
    ("cc-by-nc", r"cc by nc [1234] 0", r"creative commons attribution non ?commercial(?: [1234] 0)?"),
    ("cc-by-nd", r"cc by nd [1234] 0", r"creative commons attribution no ?deriv(?:ative)?s(?: [1234] 0)?"),
    ("cc-by", r"cc by", r"cc by"),
    ("odbl", r"odbl 1 0", r"open database"),
    ("ofl", r"ofl 1 [01]", r"(?:sil )?open font"),
    ("openssl", r"openssl", r"openssl"),
    ("postgresql", r"postgresql", r"postgresql"),
    ("vim", r"vim", r"vim"),
    ("curl", r"curl", r"curl"),
    ("w3c", r"w3c", r"w3c(?: software)?(?: notice and)?"),
    ("ms-pl", r"ms pl", r"microsoft public"),
    ("ms-rl", r"ms rl", r"microsoft reciprocal"),
    ("upl", r"upl 1 0", r"universal permissive"),
    ("afl", r"afl [123] [012]", r"academic free"),
    ("osl", r"osl [123] 0", r"open software"),
    ("ncsa", r"ncsa", r"(?:university of illinois )?ncsa(?: open source)?"),
    ("blueoak", r"blueoak 1 0 0", r"blue oak model"),
    ("elastic", r"elastic 2 0", r"elastic"),
    ("sspl", r"sspl 1 0", r"server side public"),
    ("busl", r"busl 1 1", r"business source"),
    ("beerware", r"beerware", r"beer ?ware"),
]

#: What licenses say themselves, as (label, pattern over words); NAME stands for up to twelve words.
SIGNATURES = [
    ("mit", r"permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    ("mit", r"to deal in the software without restriction"),
    ("mit", r"the above copyright notice and this permission notice (?:including the next paragraph )?shall be included in all copies or substantial portions of the software"),
    ("mit", r"the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability"),
    ("mit", r"in no event shall the authors or copyright holders be liable for any claim damages or other liability"),
    ("ncsa", r"to deal with the software without restriction"),
    ("ncsa", r"neither the names of NAME nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission"),
    ("x11", r"except as contained in this notice the names? of NAME shall not be used in advertising or otherwise to promote the sale"),
    ("isc", r"permission to use copy modify and(?: or)? distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice"),
    ("isc", r"the software is provided as is and NAME disclaims all warranties with regard to this software"),
    ("bsd-0-clause", r"permission to use copy modify and(?: or)? distribute this software for any purpose with or without fee is hereby granted the software"),
    ("bsd", r"redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("bsd", r"redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer"),
    ("bsd", r"redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer"),
    ("bsd-3-clause", r"neither the name of NAME nor the names of (?:its|any|other) contributors may be used to endorse or promote products derived"),
    ("bsd-4-clause", r"all advertising materials mentioning features or use of this software must display the following acknowledge?ment"),
    ("bsd-4-clause", r"this product includes software developed by the university of california berkeley and its contributors"),
    ("bsd-2-clause", r"the views and conclusions contained in the software and documentation are those of the authors and should not be interpreted"),
    ("bsd-3-clause-clear", r"no express or implied licen[cs]es to any party s patent rights are granted by this licen[cs]e"),
    ("apache-1.1", r"the end user documentation included with the redistribution if any must include the following acknowledg?ment"),
    ("apache-1.1", r"products derived from this software may not be called apache nor may apache appear in their name"),
    ("apache-1.1", r"this product includes software developed by the apache software foundation"),
    ("apache-2.0", r"you may not use this file except in compliance with the licen[cs]e"),
    ("apache-2.0", r"unless required by applicable law or agreed to in writing software distributed under the licen[cs]e is distributed on an as is basis"),
    ("apache-2.0", r"see the licen[cs]e for the specific language governing permissions and limitations under the licen[cs]e"),
    ("apache-2.0", r"you may obtain a copy of the licen[cs]e at https? www apache org licenses licen[cs]e 2 0"),
    ("apache-2.0", r"grant of patent licen[cs]e subject to the terms and conditions of this licen[cs]e each contributor hereby grants to you"),
    ("gpl", r"this program is free software you can redistribute it and or modify it under the terms of the gnu general public licen[cs]e"),
    ("gpl", r"you should have received a copy of the gnu general public licen[cs]e along with this (?:program|software|library)"),
    ("gpl", r"this (?:program|software) is distributed in the hope that it will be useful but without any warranty"),
    ("gpl-1.0", r"either version 1 (?:of the licen[cs]e )?or at your option any later version"),
    ("gpl-2.0", r"either version 2 (?:of the licen[cs]e )?or at your option any later version"),
    ("gpl-2.0", r"as published by the free software foundation version 2"),
    ("gpl-2.0", r"if not write to the free software foundation inc (?:51 franklin|59 temple|675 mass)"),
    ("gpl-3.0", r"either version 3 (?:of the licen[cs]e )?or at your option any later version"),
    ("gpl-3.0", r"as published by the free software foundation version 3"),
    ("gpl", r"the licen[cs]es for most software are designed to take away your freedom to share and change it"),
    ("gpl", r"everyone is permitted to copy and distribute verbatim copies of this licen[cs]e document but changing it is not allowed"),
    ("gpl", r"as a special exception the copyright holders of this library give you permission to link this library"),
    ("lgpl", r"this library is free software you can redistribute it and or modify it under the terms of the gnu (?:lesser|library) general public licen[cs]e"),
    ("lgpl", r"you should have received a copy of the gnu (?:lesser|library) general public licen[cs]e along with this"),
    ("lgpl", r"this library is distributed in the hope that it will be useful but without any warranty"),
    ("lgpl-2.1", r"either version 2 1 (?:of the licen[cs]e )?or at your option any later version"),
    ("lgpl", r"a program that contains no derivative of any portion of the library but is designed to work with the library"),
    ("agpl-3.0", r"your modified version must prominently offer all users interacting with it remotely through a computer network"),
    ("agpl", r"under the terms of the gnu affero general public licen[cs]e as published by the free software foundation"),
    ("agpl", r"you should have received a copy of the gnu affero general public licen[cs]e along with this"),
    ("fdl", r"permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation licen[cs]e"),
    ("fdl", r"with no invariant sections no front cover texts and no back cover texts"),
    ("mpl-2.0", r"this source code form is subject to the terms of the mozilla public licen[cs]e v 2 0"),
    ("mpl-2.0", r"if a copy of the mpl was not distributed with this file you can obtain one at"),
    ("mpl-2.0", r"this source code form is incompatible with secondary licen[cs]es"),
    ("mpl-1.1", r"the contents of this file are subject to the mozilla public licen[cs]e version 1 1"),
    ("mpl", r"see the licen[cs]e for the specific language governing rights and limitations under the licen[cs]e"),
    ("epl", r"this program and the accompanying materials are made available under the terms of the eclipse public licen[cs]e"),
    ("epl-1.0", r"the accompanying program is provided under the terms of this eclipse public licen[cs]e agreement"),
    ("epl", r"any use reproduction or distribution of the program constitutes recipient s acceptance of this agreement"),
    ("edl", r"made available under the terms of the eclipse distribution licen[cs]e"),
    ("cddl", r"the contents of this file are subject to the terms of the common development and distribution licen[cs]e"),
    ("cddl", r"when distributing covered code include this cddl header in each file"),
    ("cpl", r"the accompanying program is provided under the terms of this common public licen[cs]e"),
    ("eupl", r"licensed under the eupl version 1 [012]"),
    ("eupl", r"licen[cs]e under the eupl or as soon they will be approved by the european commission subsequent versions"),
    ("artistic", r"the intent of this document is to state the conditions under which a package may be copied"),
    ("artistic", r"this licen[cs]e establishes the terms under which a given free software package may be copied modified distributed and or redistributed"),
    ("perl", r"you can redistribute it and or modify it under the same terms as perl itself"),
    ("python", r"psf hereby grants licensee a nonexclusive royalty free world ?wide licen[cs]e"),
    ("python", r"beopen com licen[cs]e agreement for python"),
    ("php", r"this product includes php software freely available from"),
    ("php", r"products derived from this software may not be called php nor may php appear in their name"),
    ("ruby", r"you may make and give away verbatim copies of the source form of the software without restriction"),
    ("zlib", r"this software is provided as is without any express or implied warranty in no event will the authors be held liable"),
    ("zlib", r"the origin of this software must not be misrepresented you must not claim that you wrote the original software"),
    ("zlib", r"altered source versions must be plainly marked as such and must not be misrepresented as being the original software"),
    ("zlib", r"this notice may not be removed or altered from any source distribution"),
    ("libpng", r"the png reference library is supplied as is"),
    ("boost", r"permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this licen[cs]e"),
    ("unlicense", r"this is free and unencumbered software released into the public domain"),
    ("unlicense", r"anyone is free to copy modify publish use compile sell or distribute this software"),
    ("unlicense", r"dedicate any and all copyright interest in the software to the public domain"),
    ("wtfpl", r"everyone is permitted to copy and distribute verbatim or modified copies of this licen[cs]e document"),
    ("wtfpl", r"do what the fuck you want to"),
    ("public-domain", r"this (?:file|code|software|work) is (?:hereby )?(?:placed )?in the public domain"),
    ("public-domain", r"the authors? hereby disclaims? copyright to this source code"),
    ("public-domain", r"no copyright is claimed in the united states under title 17"),
    ("cc0", r"has waived all copyright and related or neighboring rights"),
    ("cc0", r"the person who associated a work with this deed has dedicated the work to the public domain"),
    ("cc-by", r"you must give appropriate credit provide a link to the licen[cs]e and indicate if changes were made"),
    ("cc-by-sa", r"if you remix transform or build upon the material you must distribute your contributions under the same licen[cs]e"),
    ("cc-by-nc", r"you may not use the material for commercial purposes"),
    ("cc-by-nd", r"if you remix transform or build upon the material you may not distribute the modified material"),
    ("odbl", r"this NAME is made available under the open database licen[cs]e"),
    ("ofl", r"this font software is licensed under the sil open font licen[cs]e"),
    ("ofl", r"the fonts and derivatives however cannot be released under any other type of licen[cs]e"),
    ("openssl", r"this product includes software developed by the openssl project for use in the openssl toolkit"),
    ("openssl", r"this product includes cryptographic software written by eric young"),
    ("postgresql", r"permission to use copy modify and distribute this software and its documentation for any purpose without fee and without a written agreement is hereby granted"),
    ("hpnd", r"permission to use copy modify and distribute this software and its documentation for any purpose and without fee is hereby granted"),
    ("vim", r"you can also distribute modified vim under one of the following"),
    ("curl", r"except as contained in this notice the name of a copyright holder shall not be used in advertising"),
    ("w3c", r"permission to copy modify and distribute this (?:software|work) (?:and its documentation )?with or without modification for any purpose and without fee or royalty is hereby granted"),
    ("ms-pl", r"if you begin patent litigation against any contributor over patents that you claim are infringed by the software"),
    ("ms-rl", r"for any file you distribute that contains code from the software in source code or binary format you must provide recipients the source code"),
    ("upl", r"subject to the condition set forth below permission is hereby granted to any person obtaining a copy of this software"),
    ("afl", r"this academic free licen[cs]e (?:the licen[cs]e )?applies to any original work of authorship"),
    ("osl", r"this open software licen[cs]e (?:the licen[cs]e )?applies to any original work of authorship"),
    ("blueoak", r"this licen[cs]e gives everyone as much permission to work with this software as possible"),
    ("elastic", r"you may not provide the software to third parties as a hosted or managed service"),
    ("sspl", r"if you make the functionality of the program or a modified version available to third parties as a service"),
    ("busl", r"the licensor hereby grants you the right to copy modify create derivative works redistribute and make non production use of the licensed work"),
    ("json", r"the software shall be used for good not evil"),
    ("beerware", r"if we meet some day and you think this stuff is worth it you can buy me a beer in return"),
    ("sleepycat", r"redistributions in any form must be accompanied by information on how to obtain complete source code for the"),
    ("mulan", r"you can use this software according to the terms and conditions of the mulan psl"),
    ("tcl", r"the authors hereby grant permission to use copy modify distribute and licen[cs]e this software and its documentation for any purpose"),
    ("ijg", r"this software is based in part on the work of the independent jpeg group"),
    ("freetype", r"portions of this software are copyright NAME the freetype project"),
    ("unicode", r"permission is hereby granted free of charge to any person obtaining a copy of the unicode data files"),
    ("proprietary", r"unauthori[sz]ed copying of this file via any medium is strictly prohibited"),
    ("proprietary", r"this software is the confidential and proprietary information of"),
    ("proprietary", r"use of this software is subject to the terms of the end user licen[cs]e agreement"),
    ("proprietary", r"no part of this (?:work|publication|software) may be reproduced NAME without (?:the )?(?:prior )?written permission"),
    ("proprietary", r"all rights reserved unauthori[sz]ed"),
]
#: Of these words one is in every signature: they open the gate for them.
ANCHORS = ["licen", "permission", "permitted", "redistribut", "distribute", "distributing", "warrant", "free software", "copyright", "public domain", "advertising", "as is", "misrepresented", "source distribution", "this product includes", "without restriction", "endorse or promote", "commercial purposes", "hosted or managed", "strictly prohibited", "proprietary", "for good not evil", "you want to", "a beer", "at your option", "invariant sections", "may not be called", "interacting with it", "of the software", "available to third", "litigation", "royalty", "of this agreement", "this software", "the software", "this document"]

#: Forms as (priority, confidence, pattern with I for identifiers and N for names).
FORMS = [
    (4, 1.0, r"spdx licen[cs]e identifier (?:I)"),
    (3, 0.95, r"(?:licensed|released|distributed|available|provided|redistributed|covered|governed) under (?:the )?(?:terms of )?(?:the )?(?:N)(?: licen[cs]e)?(?: version [0-9]+(?: [0-9]+)?)?"),
    (2, 0.9, r"(?:subject to|terms of|conditions of|accordance with) (?:the )?(?:N) licen[cs]e"),
    (1, 0.8, r"(?:N) licen[cs]e(?: version [0-9]+(?: [0-9]+)?)?"),
]
#: What the forms hold beside the name; a rule whose name makes these optional opens the gate by its own keywords.
GATE = ["licen", "spdx", " under ", " subject to ", " terms of ", " conditions of ", " accordance with "]
EDGE = ("(?<= )", "(?= )")
WORD = "[a-z0-9\u0080-\U0010ffff]+"


@dataclass(frozen=True)
class Rule:
    number: int
    label: str
    keywords: tuple[str, ...]
    pattern: str
    priority: int
    confidence: float
    gate: tuple[str, ...]


def _choices(parsed) -> list[set[str]]:
    """Sets of strings, of each of which every match of a parsed pattern holds one."""
    out, run = [], ""
    for op, arg in [*parsed, (None, None)]:
        if op is LITERAL:
            run += chr(arg)
            continue
        if run:
            out.append({run})
        before, run = [(LITERAL, ord(x)) for x in run], ""
        if op is SUBPATTERN:
            out += _choices(arg[-1])
        elif op is MAX_REPEAT and arg[0] > 0:
            out += _choices(arg[2])
        elif op is BRANCH:
            best = [_best(_choices([*before, *x])) for x in arg[1]]  # the parser takes out common beginnings
            if all(best):
                out.append(set().union(*best))
    return out


def _best(choices: list[set[str]]) -> set[str]:
    """The set whose shortest string is the longest; none: the empty set."""
    return max(choices, key=lambda c: min(map(len, c)), default=set())


def keywords(pattern: str) -> tuple[str, ...]:
    """Strings of which one is in every text where ``pattern`` matches between spaces; alternatives outside brackets have their own."""
    parts, depth = [""], 0
    for ch in pattern:
        depth += (ch == "(") - (ch == ")")
        if ch == "|" and not depth:
            parts.append("")
        else:
            parts[-1] += ch
    best = [_best(_choices(parse(f" {x} "))) for x in parts]
    assert all(best), pattern
    return tuple(sorted(set().union(*best)))


def rules() -> list[Rule]:
    """All families in all forms, and then the signatures, in order: over four hundred rules."""
    out = []
    for label, ident, name in FAMILIES:
        for priority, confidence, form in FORMS:
            if "licen" in name:  # the name says it already
                form = form.replace("(?:N) licen[cs]e", "(?:N)")
            body = form.replace("(?:I)", f"(?:{ident})").replace("(?:N)", f"(?:{name})")
            # A name stands between spaces in every form.
            held = ("spdx licen",) if priority == 4 else keywords(name)
            gate = held if form.startswith("(?:N)") and "licen" in name else tuple(GATE)
            out.append(Rule(len(out), label, held, EDGE[0] + body + EDGE[1], priority, confidence, gate))
    for label, pattern in SIGNATURES:
        body = pattern.replace("NAME", f"(?:{WORD} ){{0,11}}{WORD}")
        held = keywords(body)
        gate = tuple(next((a for a in ANCHORS if a in k), k) for k in held)  # every match holds a keyword, and so its anchor
        out.append(Rule(len(out), label, held, EDGE[0] + body + EDGE[1], 5, 0.97, gate))
    return out


def normal(text: Column) -> Column:
    """`` word word ``: lower-case words with one space before, between and after; no words: one space.

    Lower-casing reaches other letters than A-Z too; that makes no word longer, shorter or another
    one of the phrases, which are of letters that no other character's lower case gives.
    """
    return F.concat(F.lit(" "), F.ltrim(F.regexp_replace(F.concat(F.lower(F.coalesce(text, F.lit(""))), F.lit(" ")), r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", " ")))


def _spots(s: Column, pattern: Column) -> Column:
    """The [start, end) of each match, in characters, from the pieces between matches."""
    hits = F.regexp_extract_all(s, pattern, F.lit(0))
    gaps = F.split(s, pattern, -1)
    zero = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<s:int,e:int>>").alias("got"))
    step = lambda acc, z: F.struct((acc["at"] + F.length(z["g"]) + F.length(z["h"])).alias("at"), F.concat(acc["got"], F.array(F.struct((acc["at"] + F.length(z["g"])).alias("s"), (acc["at"] + F.length(z["g"]) + F.length(z["h"])).alias("e")))).alias("got"))
    return F.aggregate(F.filter(F.arrays_zip(gaps.alias("g"), hits.alias("h")), lambda z: z["h"].isNotNull()), zero, step, lambda acc: acc["got"])


def detect(docs: DataFrame, *, text: str = "text", extra: list[Rule] | None = None, gated: bool = True) -> DataFrame:
    """``docs`` with _norm and detections: array of (s, e, rule, label, priority, confidence), after suppression.

    Positions are characters of the normal form.  Null texts have none; each input row gives one
    output row, so repeated rows and clashing ids don't matter; columns named as the added ones are replaced.  Without ``gated`` all rules are tried on
    all texts, with the same detections.
    """
    families: dict[tuple[str, ...], list[Rule]] = {}
    every = [*rules(), *(extra or [])]
    for r in every:
        families.setdefault(r.keywords if gated else ("",), []).append(r)
    one = lambda r: F.struct(F.lit(r.pattern).alias("re"), F.lit(r.number).alias("rule"), F.lit(r.label).alias("label"), F.lit(r.priority).alias("priority"), F.lit(r.confidence).alias("confidence"))
    table = F.array(*[F.struct(F.array(*map(F.lit, k)).alias("k"), F.array(*map(one, rs)).alias("rules")) for k, rs in families.items()])
    tried = F.flatten(F.transform(F.filter(table, lambda f: F.exists(f["k"], lambda k: F.contains(F.col("_norm"), k))), lambda f: f["rules"]))
    tried = F.filter(tried, lambda r: F.regexp_like(F.col("_norm"), r["re"]))
    found = F.flatten(F.transform(tried, lambda r: F.transform(_spots(F.col("_norm"), r["re"]), lambda z: F.struct(z["s"].alias("s"), z["e"].alias("e"), r["rule"].alias("rule"), r["label"].alias("label"), r["priority"].alias("priority"), r["confidence"].alias("confidence")))))
    words = sorted({g for r in every for g in r.gate})
    gate = F.lit(not gated)
    for word in (w for w in words if not any(v != w and v in w for v in words)):
        gate = gate | F.contains(F.col("_norm"), F.lit(word))
    empty = F.array().cast("array<struct<s:int,e:int,rule:int,label:string,priority:int,confidence:double>>")

    def covers(e, d):
        wider = (e["e"] - e["s"]) - (d["e"] - d["s"])
        return (e["s"] <= d["s"]) & (e["e"] >= d["e"]) & ((e["priority"] > d["priority"]) | ((e["priority"] == d["priority"]) & ((wider > 0) | ((wider == 0) & (e["rule"] < d["rule"])))))

    every_one, names = free_name(docs.columns, "_all"), [c for c in docs.columns if c.lower() not in ("_norm", "detections")]
    out = docs.select(*map(column, names), normal(column(text)).alias("_norm"))
    out = out.select(*map(column, names), "_norm", F.when(gate, found).otherwise(empty).alias(every_one))
    return out.select(*map(column, names), "_norm", F.filter(every_one, lambda d: ~F.exists(every_one, lambda e: covers(e, d))).alias("detections"))


def digest(docs: DataFrame, **options) -> DataFrame:
    """Words, base places and labels of every document; a null text is an empty one, equal rows stay separate, an empty table stays empty."""
    d = detect(docs.select("doc_id", "text"), **options)
    pattern = EDGE[0] + "(?:" + "|".join(BASE) + ")" + EDGE[1]
    some = F.lit(False)
    for p in BASE:
        some = some | F.contains(F.col("_norm"), F.lit(f" {p} "))
    d = d.withColumn("_base", F.when(some, _spots(F.col("_norm"), F.lit(pattern))))
    before = lambda at: (F.length(F.substring("_norm", F.lit(1), at)) - F.length(F.replace(F.substring("_norm", F.lit(1), at), F.lit(" "))) - 1).cast("long")
    base = F.array_compact(F.array(*[F.when(F.contains(F.col("_norm"), F.lit(f" {p} ")), F.lit(label)) for p, label in BASE.items()]))
    own = F.transform("detections", lambda x: x["label"])
    listed = lambda a: F.array_join(F.array_sort(F.array_distinct(a)), ",")
    return d.select(
        "doc_id",
        (F.length("_norm") - F.length(F.replace("_norm", F.lit(" "))) - 1).cast("long").alias("n_words"),
        F.when(F.col("_base").isNull(), 0).otherwise(F.size("_base")).cast("long").alias("n_base"),
        F.when(F.size("_base") > 0, before(F.element_at("_base", 1)["s"])).alias("first_word"),
        F.when(F.size("_base") > 0, before(F.element_at("_base", -1)["s"])).alias("last_word"),
        listed(base).alias("base_labels"),
        listed(F.concat(base, own)).alias("labels"),
        F.coalesce(F.array_max(F.transform("detections", lambda x: x["confidence"])), F.lit(0.0)).alias("score"),
    )
