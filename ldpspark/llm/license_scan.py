"""License scans: ordered signature rules on words, gated by keywords, with priorities and interval containment.

A rule is a sequence of word patterns with a label, a priority (0 wins) and a keyword. Texts are brought to words, and
each word of a text that holds any gate keyword gets its place: "licensed_4 under_5". Rules become regular expressions on
that form whose groups catch the places of their first and last word, so detections are intervals of words. A rule runs
only on texts that hold its keyword or, where a match can lack that, words that every match has. Detections are swept by
rising start, falling end and priority; one that lies within an earlier one of the same or a better priority is suppressed.
The labels of the rest are the method's.

All is done row by row in SQL functions; nothing is shuffled. The three base phrases are counted apart from the rules.

Defined results: null and empty texts have no words and no labels; repeated rows are scanned one by one.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common as C

#: Fixed by the contract of the query: phrase and base label.
BASE = [("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved")]
#: Gates of the rules' keywords; rules whose matches can lack their keyword have gates of their own (NEEDED).
GATES = ["licen", "cc by", "rights reserved", "creative commons", "public domain", "cc0", "gpl", "copyright", "warrant", "copyleft"]
L, V = "(?:license|licence)", "(?:version|v|ver)"
#: Families: label, name as word patterns, words of its identifier, words of its address (or none).
FAMILIES = [
    ("mit", "(?:mit|expat)", "mit", "opensource org licenses mit"), ("mit-0", "mit no attribution", "mit 0", ""), ("isc", "isc", "isc", "opensource org licenses isc"),
    ("apache-1.1", f"apache software? {L}? {V}? 1 1", "apache 1 1", "apache org licenses license 1 1"), ("apache-2.0", f"apache software? {L}? {V}? 2 0?", "apache 2 0", "apache org licenses license 2 0"),
    ("bsd-2-clause", "(?:simplified|freebsd) bsd", "bsd 2 clause", "opensource org licenses bsd 2 clause"), ("bsd-2-clause", "bsd (?:2|two) clause", "bsd 2 clause", ""),
    ("bsd-3-clause", "(?:new|revised|modified) bsd", "bsd 3 clause", "opensource org licenses bsd 3 clause"), ("bsd-3-clause", "bsd (?:3|three) clause", "bsd 3 clause", ""),
    ("bsd-4-clause", "(?:original|old) bsd", "bsd 4 clause", ""), ("0bsd", "(?:zero|0) clause bsd", "0bsd", ""), ("bsd", "bsd", "bsd", ""),
    ("gpl-1.0", f"gnu? (?:gpl|general) (?:public|{V}|v1) {L}? {V}? (?:1|v1) 0?", "gpl 1 0", "gnu org licenses gpl 1 0"),
    ("gpl-2.0", f"gnu? general public {L} {V}? (?:2|v2) 0?", "gpl 2 0", "gnu org licenses gpl 2 0"), ("gpl-2.0", f"gnu? gpl {V}? (?:2|v2) 0?", "gpl 2 0 only", "gnu org licenses old licenses gpl 2 0"),
    ("gpl-2.0-or-later", f"gnu? general public {L} {V} 2 or at? your? option? any? later", "gpl 2 0 or later", ""),
    ("gpl-3.0", f"gnu? general public {L} {V}? (?:3|v3) 0?", "gpl 3 0", "gnu org licenses gpl 3 0"), ("gpl-3.0", f"gnu? gpl {V}? (?:3|v3) 0?", "gpl 3 0 only", ""),
    ("gpl-3.0-or-later", f"gnu? general public {L} {V} 3 or at? your? option? any? later", "gpl 3 0 or later", ""),
    ("lgpl-2.0", f"gnu? (?:library|lesser) general public {L} {V}? 2 0", "lgpl 2 0", "gnu org licenses lgpl 2 0"), ("lgpl-2.1", f"gnu? lesser general public {L} {V}? 2 1", "lgpl 2 1", "gnu org licenses lgpl 2 1"),
    ("lgpl-3.0", f"gnu? lesser general public {L} {V}? 3 0?", "lgpl 3 0", "gnu org licenses lgpl 3 0"), ("lgpl", f"gnu? (?:lesser|library) general public", "lgpl", "gnu org licenses lgpl"),
    ("agpl-1.0", f"affero general public {L} {V}? 1 0?", "agpl 1 0", ""), ("agpl-3.0", f"gnu? affero general public {L} {V}? 3 0?", "agpl 3 0", "gnu org licenses agpl 3 0"), ("agpl", "gnu? affero general public", "agpl", "gnu org licenses agpl"),
    ("gfdl-1.1", f"gnu? free documentation {L} {V}? 1 1", "gfdl 1 1", ""), ("gfdl-1.2", f"gnu? free documentation {L} {V}? 1 2", "gfdl 1 2", ""), ("gfdl-1.3", f"gnu? free documentation {L} {V}? 1 3", "gfdl 1 3", ""), ("gfdl", "gnu? free documentation", "gfdl", "gnu org licenses fdl"),
    ("mpl-1.0", f"mozilla public {L} {V}? 1 0", "mpl 1 0", ""), ("mpl-1.1", f"mozilla public {L} {V}? 1 1", "mpl 1 1", "mozilla org mpl mpl 1 1"), ("mpl-2.0", f"mozilla public {L} {V}? 2 0", "mpl 2 0", "mozilla org mpl 2 0"), ("mpl", "mozilla public", "mpl", ""),
    ("epl-1.0", f"eclipse public {L} {V}? 1 0", "epl 1 0", "eclipse org legal epl v10"), ("epl-2.0", f"eclipse public {L} {V}? 2 0", "epl 2 0", "eclipse org legal epl 2 0"), ("epl", "eclipse public", "epl", ""),
    ("cddl-1.0", "common development and distribution", "cddl 1 0", ""), ("cpl-1.0", "common public", "cpl 1 0", ""), ("eupl-1.1", f"european union public {L} {V}? 1 1", "eupl 1 1", ""), ("eupl-1.2", f"european union public {L} {V}? 1 2", "eupl 1 2", ""), ("eupl", "european union public", "eupl", ""),
    ("artistic-1.0", f"artistic {L} {V}? 1 0", "artistic 1 0", ""), ("artistic-2.0", f"artistic {L} {V}? 2 0", "artistic 2 0", ""), ("artistic", "artistic", "artistic", ""), ("bsl-1.0", "boost software", "bsl 1 0", "boost org license 1 0"), ("busl-1.1", "business source", "busl 1 1", ""),
    ("zlib", "zlib", "zlib", ""), ("libpng", "libpng", "libpng", ""), ("openssl", "openssl", "openssl", ""), ("postgresql", "postgresql", "postgresql", ""), ("python-2.0", "python software foundation", "python 2 0", ""), ("php-3.0", "php", "php 3 01", ""), ("ruby", "ruby", "ruby", ""),
    ("unlicense", "unlicense", "unlicense", "unlicense org"), ("wtfpl", "do what the? \\w+ you want to? public", "wtfpl", ""), ("w3c", "w3c software notice? and?", "w3c", ""), ("ms-pl", "microsoft public", "ms pl", ""), ("ms-rl", "microsoft reciprocal", "ms rl", ""),
    ("osl-3.0", "open software", "osl 3 0", ""), ("afl-3.0", "academic free", "afl 3 0", ""), ("qpl-1.0", "q public", "qpl 1 0", ""), ("ofl-1.1", "sil open font", "ofl 1 1", "scripts sil org ofl"), ("odbl-1.0", "open database", "odbl 1 0", "opendatacommons org licenses odbl"), ("odc-by-1.0", "open data commons attribution", "odc by 1 0", ""),
    ("pddl-1.0", "open data commons public domain dedication", "pddl 1 0", ""), ("ncsa", "university of illinois ncsa", "ncsa", ""), ("upl-1.0", "universal permissive", "upl 1 0", ""), ("vim", "vim", "vim", ""), ("x11", "x11", "x11", ""), ("elastic-2.0", "elastic", "elastic 2 0", ""), ("sspl-1.0", "server side public", "sspl 1 0", ""),
    ("openrail", "(?:open|bigscience|creativeml) (?:rail|openrail)", "openrail", ""), ("llama", "llama \\d* ?community", "llama", ""), ("mulan-2.0", "mulan permissive software", "mulanpsl 2 0", ""), ("cecill-2.1", "cecill", "cecill 2 1", ""), ("ogl-uk-3.0", "open government", "ogl uk 3 0", "nationalarchives gov uk doc open government licence"),
]
CC_PARTS = [("by", "attribution"), ("by-sa", "attribution share ?alike"), ("by-nd", "attribution no ?derivs"), ("by-nc", "attribution non ?commercial"), ("by-nc-sa", "attribution non ?commercial share ?alike"), ("by-nc-nd", "attribution non ?commercial no ?derivs")]
CC_VERSIONS = ["1.0", "2.0", "2.5", "3.0", "4.0"]
NOTICES = [
    ("copyright", 2, "copyright", "copyright c? (?:19|20)\\d\\d"), ("no-warranty", 2, "warrant", "without warranty of any kind"), ("no-warranty", 2, "warrant", "without warranties or conditions of any kind"), ("public-domain", 1, "public domain", "(?:in|into|to) the public domain"),
    ("public-domain", 1, "public domain", "dedicated to the public domain"), ("public-domain", 1, "public domain", "released into the public domain"), ("cc0-1.0", 0, "cc0", "cc0 1 0 universal?"), ("cc0-1.0", 1, "creative commons", "creative commons zero"), ("cc0-1.0", 1, "cc0", "cc0"),
    ("cc", 2, "creative commons", "creative commons"), ("mit", 1, "licen", "permission is hereby granted free of charge to any person obtaining a copy"), ("bsd", 1, "licen", "redistribution and use in source and binary forms with or without modification"),
    ("apache-2.0", 1, "licen", f"you may not use this file except in compliance with the {L}"), ("proprietary", 2, "licen", "this software is (?:proprietary|confidential)"), ("copyleft", 2, "copyleft", "copyleft"), ("gpl", 2, "gpl", "gnu? gpl"), ("gpl", 2, "licen", f"gnu? general public {L}"),
    ("unknown", 2, "licen", f"(?:licensed|released|distributed|available) under (?:the|a|an) (?:terms|following|same|commercial|proprietary|custom)"), ("commercial", 1, "licen", f"commercial {L} (?:agreement|required|only)"), ("eula", 1, "licen", f"end user {L} agreement"), ("non-commercial", 2, "licen", f"non ?commercial (?:use|purposes) {L}?"),
]


#: Sentences of the licenses' own texts and notices: label, priority, keyword, word patterns.
SIGNATURES = [
    ("mit", 1, "copyright", "the above copyright notice and this permission notice shall be included in all copies"), ("mit", 1, "licen", "to use copy modify merge publish distribute sublicense and or sell copies of the software"),
    ("mit-0", 1, "hereby granted", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction"),
    ("isc", 1, "hereby granted", "permission to use copy modify and or? distribute this software for any purpose with or without fee is hereby granted"), ("hpnd", 1, "hereby granted", "permission to use copy modify and distribute this software and its documentation for any purpose"),
    ("hpnd", 1, "copyright", "provided that the above copyright notice (?:appear|appears) in all copies and that both that copyright notice and this permission notice appear in supporting documentation"),
    ("bsd", 1, "copyright", "redistributions of source code must retain the above copyright notice"), ("bsd", 1, "copyright", "redistributions in binary form must reproduce the above copyright notice"),
    ("bsd-3-clause", 1, "endorse or promote", "neither the (?:name|names) of (?:the|its) .{0,80}?may be used to endorse or promote products"), ("bsd-3-clause", 1, "endorse or promote", "may be used to endorse or promote products derived from this software without specific prior written permission"),
    ("bsd-4-clause", 1, "advertising materials", "all advertising materials mentioning features or use of this software must display the following acknowledge?ment"), ("bsd", 2, "software is provided by the", "this software is provided by the (?:copyright|authors?|regents) (?:holders?|and|as) (?:and|contributors|is)"),
    ("apache-2.0", 1, "licen", f"unless required by applicable law or agreed to in writing software distributed under the {L} is distributed on an as is basis"), ("apache-2.0", 1, "licen", f"see the {L} for the specific language governing permissions and limitations under the {L}"),
    ("apache-2.0", 1, "licen", "licensed to the apache software foundation asf under one or more contributor license agreements"), ("apache-2.0", 1, "licen", f"subject to the terms and conditions of this {L} each contributor hereby grants to you a perpetual worldwide"),
    ("apache-1.1", 1, "developed by the apache", "this product includes software developed by the apache (?:software|group)"),
    ("gpl", 1, "redistribute it", f"this program is free software you can redistribute it and or modify it under the terms of the gnu general public {L}"), ("gpl", 1, "licen", f"you should have received a copy of the gnu general public {L} along with this"),
    ("gpl", 2, "licen", f"this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability .{{0,60}}?gnu general public {L}"),
    ("gpl-2.0-or-later", 0, "licen", f"gnu general public {L} as published by the free software foundation either {V} 2 of the {L} or at your option any later version"), ("gpl-3.0-or-later", 0, "licen", f"gnu general public {L} as published by the free software foundation either {V} 3 of the {L} or at your option any later version"),
    ("gpl-2.0", 0, "licen", f"gnu general public {L} {V} 2 only"), ("gpl-2.0", 1, "june 1991", "version 2 june 1991"), ("gpl-3.0", 1, "june 2007", "version 3 29 june 2007"), ("agpl-3.0", 1, "november 2007", "version 3 19 november 2007"), ("lgpl-2.1", 1, "february 1999", "version 2 1 february 1999"), ("gpl-1.0", 1, "february 1989", "version 1 february 1989"),
    ("lgpl", 1, "redistribute it", f"this library is free software you can redistribute it and or modify it under the terms of the gnu (?:lesser|library) general public {L}"), ("lgpl", 1, "licen", f"you should have received a copy of the gnu (?:lesser|library) general public {L} along with this"),
    ("agpl", 1, "licen", f"you should have received a copy of the gnu affero general public {L} along with this"), ("agpl", 2, "remote network", "all users interacting with it remotely through a computer network"), ("gpl", 2, "copyleft", "everyone is permitted to copy and distribute verbatim copies of this license document but changing it is not allowed"),
    ("gpl-with-classpath-exception", 0, "classpath exception", "classpath exception"), ("gpl-with-classpath-exception", 1, "linking this library", "linking this library statically or dynamically with other modules is making a combined work"), ("gpl-with-gcc-exception", 0, "runtime library exception", "gcc runtime library exception"), ("gpl-with-font-exception", 0, "font exception", "font exception"),
    ("mpl-2.0", 1, "licen", f"this source code form is subject to the terms of the mozilla public {L} {V} 2 0"), ("mpl-2.0", 1, "incompatible with secondary", "incompatible with secondary licenses as defined by the mozilla public license"), ("mpl-1.1", 1, "licen", f"the contents of this file are subject to the mozilla public {L} {V} 1 1"),
    ("epl-2.0", 1, "epl 2 0", "which is available at (?:http|https) www eclipse org legal epl 2 0"), ("epl-1.0", 1, "licen", f"made available under the terms of the eclipse public {L} v1 0"), ("cddl-1.0", 1, "licen", f"the contents of this file are subject to the terms of the common development and distribution {L}"), ("cpl-1.0", 1, "licen", "common public license v1 0"),
    ("artistic", 1, "licen", "the artistic license"), ("perl", 1, "perl itself", "under the same terms as perl itself"), ("python-2.0", 1, "python software foundation", "psf hereby grants licensee a nonexclusive royalty free world wide license"), ("php-3.0", 1, "php software", "this product includes php software freely available from"),
    ("zlib", 1, "express or implied", "this software is provided as is without any express or implied warranty in no event will the authors be held liable"), ("zlib", 1, "must not be misrepresented", "the origin of this software must not be misrepresented"), ("zlib", 2, "altered source", "altered source versions must be plainly marked as such"),
    ("bsl-1.0", 1, "hereby granted", "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license"), ("openssl", 1, "openssl project", "this product includes software developed by the openssl project"), ("ssleay", 1, "eric young", "this product includes cryptographic software written by eric young"),
    ("unlicense", 1, "free and unencumbered", "this is free and unencumbered software released into the public domain"), ("unlicense", 1, "anyone is free to copy", "anyone is free to copy modify publish use compile sell or distribute this software"), ("wtfpl", 1, "you just do what", "you just do what the \\w+ you want to"),
    ("cc0-1.0", 1, "waive", "to the extent possible under law .{0,120}?waived all copyright and related or neighboring rights"), ("cc0-1.0", 0, "publicdomain zero", "creativecommons org publicdomain zero 1 0"), ("public-domain", 1, "publicdomain mark", "creativecommons org publicdomain mark"), ("public-domain", 1, "author disclaims copyright", "the author disclaims copyright to this source code"), ("public-domain", 2, "no copyright", "no copyright is claimed"),
    ("ofl-1.1", 1, "reserved font name", "with reserved font (?:name|names)"), ("ofl-1.1", 1, "licen", f"this font software is licensed under the sil open font {L} {V} 1 1"), ("odbl-1.0", 1, "licen", f"this .{{0,40}}?is made available under the open database {L}"), ("pddl-1.0", 2, "public domain dedication", "public domain dedication and license"),
    ("ncsa", 1, "hereby granted", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal with the software without restriction"), ("curl", 1, "curl and libcurl", "curl and libcurl are licensed under"), ("x11", 1, "x consortium", "except as contained in this notice the (?:name|names) of the x consortium shall not be used"),
    ("beerware", 1, "beer ware", "the beer ware license"), ("beerware", 1, "buy me a beer", "you can buy me a beer in return"), ("json", 1, "good not evil", "the software shall be used for good not evil"), ("jpeg", 1, "independent jpeg group", "this software is based in part on the work of the independent jpeg group"), ("freetype", 1, "freetype project", "portions of this software are copyright .{0,40}?the freetype project"),
    ("unicode", 1, "unicode data files", "unicode data files and .{0,40}?software"), ("w3c", 1, "licen", "w3c software notice and license"), ("elastic-2.0", 1, "hosted or managed service", "you may not provide the software to third parties as a hosted or managed service"), ("sspl-1.0", 1, "server side public", "server side public license"), ("commons-clause", 0, "commons clause", "commons clause license condition"), ("commons-clause", 1, "right to sell", "does not grant to you the right to sell the software"),
    ("busl-1.1", 1, "additional use grant", "additional use grant"), ("polyform", 1, "polyform", "polyform (?:noncommercial|shield|perimeter|strict|internal)"), ("hippocratic", 1, "hippocratic", "hippocratic license"), ("openrail", 1, "use based restrictions", "use based restrictions as referenced in paragraph"), ("gemma", 1, "gemma terms", "gemma terms of use"), ("ai2-impact", 1, "impact license", "ai2 impact license"),
    ("proprietary", 1, "proprietary and confidential", "proprietary and confidential"), ("proprietary", 1, "unauthorized copying", "unauthorized copying of this file via any medium is strictly prohibited"),
    ("proprietary", 2, "may be reproduced", "no part of this \\w+ may be reproduced"), ("eula", 1, "by installing", "by installing .{0,40}?you agree to be bound by"), ("eula", 2, "reverse engineer", "you (?:may|shall) not reverse engineer decompile or disassemble"),
    ("non-commercial", 2, "use only", "for personal and? non ?commercial use only"), ("cc", 2, "some rights reserved", "some rights reserved"), ("unknown", 2, "see license", "see license (?:file|for|in)"), ("unknown", 2, "license agreement", "this license agreement is (?:a|made|entered)"),
    ("no-warranty", 2, "merchantability", "implied warrant(?:y|ies) of merchantability"), ("no-warranty", 2, "consequential damages", "incidental special exemplary or consequential damages"), ("no-warranty", 2, "in no event shall", "in no event shall the (?:authors?|copyright|contributors|regents) (?:or|holders?|be)"),
    ("copyright", 2, "copyright", "copyright (?:the|by|holders?)"), ("copyright", 2, "copyrighted", "this (?:work|material|document|file) is copyrighted"), ("patent-grant", 2, "patent license", "hereby grants .{0,80}?patent license"),
]


#: Words of rules that say little about which license it is.
COMMON = frozenset("licensed under with the terms public software general version free open common documentation org www license licenses creative commons attribution".split())


def numbered(words: str) -> str:
    """Regular expression on numbered words; ``w?`` is an optional word, `` ?`` within a pattern allows a break."""
    out, tokens = [], words.replace(" ?", "\x01").split(" ")
    must = [i for i, t in enumerate(tokens) if not _optional(t)]
    for i, t in enumerate(tokens):
        optional = _optional(t)
        body = (t[:-1] if optional else t).replace("\x01", r"(?:_\d+ )?")
        if i == must[0] == must[-1]:
            out.append(rf" (?:{body})_((\d+))")
        elif i in (must[0], must[-1]):
            out.append(rf" (?:{body})_(\d+)")
        else:
            out.append(rf"(?: (?:{body})_\d+)?" if optional else rf" (?:{body})_\d+")
    # what is optional before the first or after the last caught word only widens a match, not its interval
    return "".join(out)


def _optional(token: str) -> bool:
    return token.endswith("?") and not token.endswith("\\?")


def rarest(words: str) -> str:
    """The word between blanks that every match of a rule holds and that few other texts do: its longest plain one."""
    plain = [t for t in words.replace(" ?", "\x01").split(" ") if re.fullmatch(r"[a-z0-9]+", t)]
    return f" {'spdx' if 'spdx' in plain else max(plain, key=lambda t: (t not in COMMON, len(t)))} " if plain else " "


def _spellings(token: str) -> list[str] | None:
    """Texts that a word pattern stands for, if it is a plain word or a choice of such; `` ?`` in it is a blank or nothing."""
    choice = re.fullmatch(r"\(\?:([^()]*)\)", token)
    parts = choice[1].split("|") if choice else [token]
    if not all(re.fullmatch("[a-z0-9\x01]+", x) for x in parts):
        return None
    return [y for x in parts for y in ([x.replace("\x01", ""), x.replace("\x01", " ")] if "\x01" in x else [x])]


def needed(words: str, keyword: str) -> list[str]:
    """Texts of which every match of a rule holds one: its keyword, if all matches hold that, else its longest run of words."""
    runs: list[list[str]] = []
    tokens = [None if _optional(t) else _spellings(t) for t in words.replace(" ?", "\x01").split(" ")]
    for lo in range(len(tokens)):
        run = [""]
        for spelt in tokens[lo:]:
            if spelt is None or len(run) * len(spelt) > 6:
                break
            run = [f"{x} {y}" for x in run for y in spelt]
            runs.append([f"{x} " for x in run])
    if any(all(keyword in x for x in run) for run in runs):
        return [keyword]
    return max(runs, key=lambda run: (min(map(len, run)), -len(run)))


def patterns() -> list[tuple[str, int, str, str]]:
    """(label, priority, keyword, words) of every rule."""
    made: list[tuple[str, int, str, str]] = [*NOTICES, *SIGNATURES]
    grant = "(?:licensed|released|distributed|available|published|provided|covered|redistributed) (?:under|by|with) the? terms? of? the?"
    for label, name, tag, address in FAMILIES:
        made.append((label, 0, "licen", f"spdx {L} identifier {tag}"))
        closed = name if re.search(rf"\d\??$|later$|{re.escape(L)}\??$", name) else f"{name} {L}"
        made.append((label, 1, "licen", f"{grant} {closed}"))
        made.append((label, 2, "licen", closed if L in closed else f"{closed} {L}"))
        if address:
            made.append((label, 1, "licen", address))
    for part, name in CC_PARTS:
        for v in CC_VERSIONS:
            words, spoken = f"cc {part} {v}".replace("-", " ").replace(".", " "), v.replace(".", " ")
            made.append((f"cc-{part}-{v}", 0, "cc by", words))
            made.append((f"cc-{part}-{v}", 0, "creative commons", f"creative commons {name} {spoken}"))
        made.append((f"cc-{part}", 1, "cc by", f"cc {part}".replace("-", " ")))
        made.append((f"cc-{part}", 1, "creative commons", f"creative commons {name}"))
        made.append((f"cc-{part}", 1, "licen", f"creativecommons org licenses {part}".replace("-", " ")))
    return made


def rules() -> list[tuple[int, str, int, str, str, str]]:
    """(order, label, priority, keyword, rarest word, regular expression) of every rule, best priority first."""
    unique = dict.fromkeys((label, prio, word, rarest(p), numbered(p)) for label, prio, word, p in patterns())
    return [(k, *r) for k, r in enumerate(sorted(unique, key=lambda r: r[1]))]


RULES = rules()
#: Gates of a rule by keyword and regular expression, and of all rules: a text without any of these holds no detection.
NEEDED = {(word, numbered(p)): needed(p, word) for _, _, word, p in patterns()}
_ALL = dict.fromkeys([*GATES, *(x for held in NEEDED.values() for x in held)])
ANY = [x for x in _ALL if not any(y in x and y != x for y in _ALL)]
#: Of the other gates, the longest telling word of each: a text without these words holds none of them.
KEYS = sorted({max(x.split(), key=lambda t: (t not in COMMON, len(t), t)) for x in ANY if x not in GATES})
CONFIDENCE = {0: 1.0, 1: 0.9, 2: 0.6}


def _sql(text: str) -> str:
    return "r'" + text.replace("'", r"\'") + "'"


def _words(texts: list[str]) -> str:
    return ", ".join(f"'{x}'" for x in texts)


def scan(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_words, n_base, first_word, last_word, base_labels and labels (arrays), score, detections of every row.

    detections: the unsuppressed ones, as (first, last, priority, label), in order.
    """
    text = F.coalesce(text_col, F.lit(""))
    # letters are lowered one by one only where some are beyond ASCII
    lowered = F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(F.translate(text, C.UPPER, C.LOWER))
    flat = F.trim(F.regexp_replace(lowered, C.NON_WORD, " "))
    rows = docs.select(F.col(id_col), flat.alias("flat")).withColumn("norm", F.concat(F.lit(" "), "flat", F.lit(" ")))
    n_words = F.when(F.col("flat") == "", 0).otherwise(F.length("flat") - F.length(F.replace("flat", F.lit(" "), F.lit(""))) + 1).cast("long")
    held = " OR ".join(f"contains(norm, '{g}')" for g in ANY if g in GATES)
    other = " OR ".join(f"contains(norm, '{g}')" for g in ANY if g not in GATES)
    gate = f"{held} OR (arrays_overlap(split(flat, ' '), array({_words(KEYS)})) AND ({other}))"
    rows = rows.select(id_col, "norm", n_words.alias("n_words"), F.expr(f"CASE WHEN {gate} THEN concat(' ', array_join(transform(split(trim(norm), ' '), (w, i) -> concat(w, '_', i)), ' ')) END").alias("placed"))
    base = [f"transform(regexp_extract_all(placed, {_sql(numbered(p))}, 1), x -> struct(cast(x as bigint) as at, '{label}' as label))" for p, label in BASE]
    table = ", ".join(f"struct({k} as k, '{label}' as label, {prio} as prio, array({_words(NEEDED[word, p])}) as needed, '{rare}' as rare, {_sql(p)} as p)" for k, label, prio, word, rare, p in RULES)
    found = f"""flatten(transform(filter(array({table}), r -> contains(norm, r.rare) AND exists(r.needed, w -> contains(norm, w))), r -> zip_with(
        regexp_extract_all(placed, r.p, 1), regexp_extract_all(placed, r.p, 2),
        (a, b) -> struct(cast(a as int) as first, -cast(b as int) as neg, r.prio as prio, r.k as k, r.label as label))))"""
    # largest end so far by priority, in doubling steps: a fold that gathers an array would copy it for each detection
    nothing = "struct(-1 as m0, -1 as m1, -1 as m2)"
    ends = "transform(found, d -> struct(CASE WHEN d.prio = 0 THEN -d.neg ELSE -1 END as m0, CASE WHEN d.prio <= 1 THEN -d.neg ELSE -1 END as m1, -d.neg as m2))"
    reach = f"""aggregate(sequence(0, greatest(0, cast(ceil(log2(size(found))) as int) - 1)), {ends}, (m, j) ->
        zip_with(m, concat(array_repeat({nothing}, least(shiftleft(1, j), size(m))), slice(m, 1, greatest(size(m) - shiftleft(1, j), 0))),
          (x, y) -> struct(greatest(x.m0, y.m0) as m0, greatest(x.m1, y.m1) as m1, greatest(x.m2, y.m2) as m2)))"""
    swept = f"""transform(filter(zip_with(found, concat(array({nothing}), {reach}), (d, m) -> struct(d, m)),
        x -> x.d IS NOT NULL AND -x.d.neg > CASE x.d.prio WHEN 0 THEN x.m.m0 WHEN 1 THEN x.m.m1 ELSE x.m.m2 END),
        x -> struct(x.d.first as first, -x.d.neg as last, x.d.prio as prio, x.d.label as label))"""
    none = "cast(array() as array<struct<first:int,last:int,prio:int,label:string>>)"
    rows = rows.withColumn("base", F.expr(f"CASE WHEN placed IS NOT NULL THEN concat({', '.join(base)}) ELSE cast(array() as array<struct<at:bigint,label:string>>) END"))
    rows = rows.withColumn("found", F.expr(f"CASE WHEN placed IS NOT NULL THEN sort_array({found}) END")).withColumn("detections", F.expr(f"CASE WHEN size(found) > 0 THEN {swept} ELSE {none} END"))
    score = " ".join(f"WHEN exists(detections, d -> d.prio = {p}) THEN {c}D" for p, c in CONFIDENCE.items())
    return rows.select(
        id_col, "n_words", F.size("base").cast("long").alias("n_base"), F.expr("array_min(transform(base, b -> b.at))").alias("first_word"), F.expr("array_max(transform(base, b -> b.at))").alias("last_word"),
        F.expr("array_sort(array_distinct(transform(base, b -> b.label)))").alias("base_labels"), F.expr("array_sort(array_distinct(concat(transform(base, b -> b.label), transform(detections, d -> d.label))))").alias("labels"),
        F.expr(f"CASE {score} WHEN size(base) > 0 THEN 0.5D ELSE 0D END").alias("score"), "detections",
    )


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract digest of :func:`scan` over ``documents``."""
    found = scan(C.table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "n_base", "first_word", "last_word", F.array_join("base_labels", ",").alias("base_labels"), F.array_join("labels", ",").alias("labels"), "score")


def _values(rows: list[tuple]) -> str:
    return ", ".join("(" + ", ".join(str(x) if isinstance(x, int) else "'" + x.replace("'", "''") + "'" for x in r) + ")" for r in rows)


OP1_SQL = rf"""
WITH t AS (SELECT doc_id, trim(regexp_replace(translate(coalesce(text, ''), '{C.UPPER}', '{C.LOWER}'), '{C.NON_WORD}', ' ', 'g')) AS flat FROM documents),
w AS (SELECT doc_id, flat, CASE WHEN flat = '' THEN [] ELSE string_split(flat, ' ') END AS words FROM t),
p AS (SELECT doc_id, CAST(len(words) AS BIGINT) AS n_words, ' ' || flat || ' ' AS norm, ' ' || array_to_string(list_transform(words, lambda x, i: x || '_' || (i - 1)), ' ') AS placed FROM w),
b AS (SELECT doc_id, label, CAST(unnest(regexp_extract_all(placed, pat, 1)) AS BIGINT) AS place FROM p, (VALUES {_values([(numbered(p), label) for p, label in BASE])}) AS r(pat, label)),
bs AS (SELECT doc_id, count(*) AS n_base, min(place) AS first_word, max(place) AS last_word, string_agg(DISTINCT label, ',' ORDER BY label) AS base_labels FROM b GROUP BY doc_id),
r(k, label, prio, word, rare, pat) AS (VALUES {_values(RULES)}),
f AS (SELECT doc_id, k, label, prio, unnest(regexp_extract_all(placed, pat, 1)) AS a, unnest(regexp_extract_all(placed, pat, 2)) AS z FROM p JOIN r ON contains(norm, rare)),
d AS (SELECT doc_id, k, label, prio, CAST(a AS INTEGER) AS a, CAST(z AS INTEGER) AS z FROM f),
m AS (SELECT *, max(CASE WHEN prio = 0 THEN z END) OVER o AS m0, max(CASE WHEN prio <= 1 THEN z END) OVER o AS m1, max(z) OVER o AS m2 FROM d
  WINDOW o AS (PARTITION BY doc_id ORDER BY a, z DESC, prio, k, label ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
kept AS (SELECT doc_id, label, prio FROM m WHERE z > coalesce(CASE prio WHEN 0 THEN m0 WHEN 1 THEN m1 ELSE m2 END, -1)),
l AS (SELECT doc_id, string_agg(DISTINCT label, ',' ORDER BY label) AS labels, min(prio) AS prio FROM (SELECT * FROM kept UNION ALL SELECT doc_id, label, 3 FROM b) GROUP BY doc_id)
SELECT p.doc_id, n_words, coalesce(n_base, 0) AS n_base, first_word, last_word, coalesce(base_labels, '') AS base_labels, coalesce(labels, '') AS labels,
  CAST(CASE l.prio WHEN 0 THEN 1.0 WHEN 1 THEN 0.9 WHEN 2 THEN 0.6 WHEN 3 THEN 0.5 ELSE 0 END AS DOUBLE) AS score
FROM p LEFT JOIN bs USING (doc_id) LEFT JOIN l USING (doc_id)
"""
