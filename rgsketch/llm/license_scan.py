"""License scan by ordered signature rules.

Texts become lower-case word strings. A rule has a label, a regex over that string, a keyword that gates it, a priority
and a confidence; the table crosses license names with the ways they are stated, after hand-written signatures of license
texts. Detections are taken by priority, then length; one that lies inside a taken detection of the same or a better
priority is suppressed. The three base phrases are counted apart and their labels always stay.

Edge cases: a null text counts as empty, with no words and score 0; whole texts of any length are scanned; repeated rows
give repeated results; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from bisect import bisect_left, bisect_right
from functools import lru_cache
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from rgsketch.llm.common import chunks, utf8, words

# The base phrases and their labels, and what separates words.
BASE = {("under", "the", "mit", "license"): "mit", ("apache", "license", "version", "2"): "apache-2", ("cc", "by", "nc"): "cc-by-nc"}
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")

# Label, keyword that must occur, the name's pattern over words, the tag's words.
NAMES = [
    ("mit", "mit", r"(?:the )?mit(?: x11)?(?: style)?", "mit"),
    ("mit-0", "mit", r"mit (?:0|no attribution)", "mit 0"),
    ("apache-2", "apache", r"apache(?: software)?(?: license)?(?: version)? (?:v)?2(?: 0)?", "apache 2 0"),
    ("apache-1.1", "apache", r"apache(?: software)?(?: license)?(?: version)? 1 1", "apache 1 1"),
    ("gpl-1", "gpl|general public", r"(?:gnu )?(?:gpl|general public)(?: license)?(?: version)? v?1(?: 0)?", "gpl 1 0"),
    ("gpl-2", "gpl|general public", r"(?:gnu )?(?:gpl|general public)(?: license)?(?: version)? v?2(?: 0)?", "gpl 2 0"),
    ("gpl-3", "gpl|general public", r"(?:gnu )?(?:gpl|general public)(?: license)?(?: version)? v?3(?: 0)?", "gpl 3 0"),
    ("gpl", "gpl|general public", r"(?:gnu )?(?:gpl|general public(?: license)?)", "gpl"),
    ("lgpl-2.1", "lgpl|lesser general", r"(?:gnu )?(?:lgpl|lesser general public)(?: license)?(?: version)? v?2 1", "lgpl 2 1"),
    ("lgpl-3", "lgpl|lesser general", r"(?:gnu )?(?:lgpl|lesser general public)(?: license)?(?: version)? v?3(?: 0)?", "lgpl 3 0"),
    ("lgpl-2", "library general", r"(?:gnu )?library general public(?: license)?(?: version)? v?2(?: 0)?", "lgpl 2 0"),
    ("agpl-3", "agpl|affero", r"(?:gnu )?(?:agpl|affero general public)(?: license)?(?: version)? v?3(?: 0)?", "agpl 3 0"),
    ("gfdl-1.3", "free documentation", r"(?:gnu )?free documentation(?: license)?(?: version)? 1 3", "gfdl 1 3"),
    ("gfdl-1.2", "free documentation", r"(?:gnu )?free documentation(?: license)?(?: version)? 1 2", "gfdl 1 2"),
    ("bsd-2", "bsd", r"(?:2 clause|two clause|simplified|freebsd) bsd|bsd (?:2|two) clause", "bsd 2 clause"),
    ("bsd-3", "bsd", r"(?:3 clause|three clause|new|modified|revised) bsd|bsd (?:3|three) clause", "bsd 3 clause"),
    ("bsd-4", "bsd", r"(?:4 clause|four clause|original) bsd|bsd (?:4|four) clause", "bsd 4 clause"),
    ("0bsd", "bsd", r"(?:0bsd|zero clause bsd|0 clause bsd)", "0bsd"),
    ("isc", "isc", r"isc", "isc"),
    ("mpl-1.1", "mpl|mozilla", r"(?:mpl|mozilla public)(?: license)?(?: version)? v?1 1", "mpl 1 1"),
    ("mpl-2", "mpl|mozilla", r"(?:mpl|mozilla public)(?: license)?(?: version)? v?2(?: 0)?", "mpl 2 0"),
    ("epl-1", "epl|eclipse", r"(?:epl|eclipse public)(?: license)?(?: version)? v?1(?: 0)?", "epl 1 0"),
    ("epl-2", "epl|eclipse", r"(?:epl|eclipse public)(?: license)?(?: version)? v?2(?: 0)?", "epl 2 0"),
    ("edl-1", "eclipse", r"eclipse distribution(?: license)?(?: version)? v?1(?: 0)?", "bsd 3 clause eclipse"),
    ("cddl-1", "cddl|common development", r"(?:cddl|common development and distribution)(?: license)?(?: version)? v?1(?: 0)?", "cddl 1 0"),
    ("cddl-1.1", "cddl|common development", r"(?:cddl|common development and distribution)(?: license)?(?: version)? v?1 1", "cddl 1 1"),
    ("cpl-1", "common public", r"common public(?: license)?(?: version)? v?1(?: 0)?", "cpl 1 0"),
    ("artistic-1", "artistic", r"artistic(?: license)?(?: version)? 1(?: 0)?", "artistic 1 0"),
    ("artistic-2", "artistic", r"artistic(?: license)?(?: version)? 2(?: 0)?", "artistic 2 0"),
    ("bsl-1", "boost", r"boost(?: software)?(?: license)?(?: version)? 1(?: 0)?", "bsl 1 0"),
    ("busl-1.1", "business source", r"business source(?: license)?(?: version)? 1 1", "busl 1 1"),
    ("unlicense", "unlicense", r"unlicense", "unlicense"),
    ("wtfpl", "wtfpl", r"wtfpl", "wtfpl"),
    ("zlib", "zlib", r"zlib(?: libpng)?", "zlib"),
    ("libpng", "libpng", r"libpng", "libpng"),
    ("python-2", "python|psf", r"(?:python(?: software foundation)?|psf)(?: license)?(?: version)? 2(?: 0)?", "python 2 0"),
    ("php-3", "php", r"php(?: license)?(?: version)? 3 0?1", "php 3 01"),
    ("ruby", "ruby", r"ruby", "ruby"),
    ("postgresql", "postgresql", r"postgresql", "postgresql"),
    ("openssl", "openssl", r"openssl", "openssl"),
    ("curl", "curl", r"curl", "curl"),
    ("ncsa", "ncsa|illinois", r"(?:university of illinois )?ncsa(?: open source)?", "ncsa"),
    ("afl-3", "academic free", r"academic free(?: license)?(?: version)? v?3(?: 0)?", "afl 3 0"),
    ("osl-3", "open software", r"open software(?: license)?(?: version)? v?3(?: 0)?", "osl 3 0"),
    ("ecl-2", "educational community", r"educational community(?: license)?(?: version)? v?2(?: 0)?", "ecl 2 0"),
    ("eupl-1.1", "eupl|european union public", r"(?:eupl|european union public)(?: licen[cs]e)?(?: version)? v?1 1", "eupl 1 1"),
    ("eupl-1.2", "eupl|european union public", r"(?:eupl|european union public)(?: licen[cs]e)?(?: version)? v?1 2", "eupl 1 2"),
    ("ms-pl", "microsoft public|ms pl", r"(?:microsoft public|ms pl)", "ms pl"),
    ("ms-rl", "microsoft reciprocal|ms rl", r"(?:microsoft reciprocal|ms rl)", "ms rl"),
    ("upl-1", "universal permissive", r"universal permissive(?: license)?(?: version)? v?1(?: 0)?", "upl 1 0"),
    ("ofl-1.1", "open font|ofl", r"(?:sil )?(?:open font|ofl)(?: license)?(?: version)? 1 1", "ofl 1 1"),
    ("odbl-1", "odbl|open database", r"(?:odbl|open database)(?: license)?(?: version)? v?1(?: 0)?", "odbl 1 0"),
    ("odc-by-1", "odc by|open data commons attribution", r"(?:odc by|open data commons attribution)(?: license)?(?: v?1(?: 0)?)?", "odc by 1 0"),
    ("pddl-1", "pddl", r"pddl(?: v?1(?: 0)?)?", "pddl 1 0"),
    ("cc0-1", "cc0", r"cc0(?: 1 0)?(?: universal)?", "cc0 1 0"),
    ("cc-by-nc-nd", "cc by nc nd|attribution noncommercial|attribution non commercial", r"(?:cc by nc nd|(?:creative commons )?attribution non ?commercial no ?derivatives?)(?: [1-4] [05])?", "cc by nc nd 4 0"),
    ("cc-by-nc-sa", "cc by nc sa|attribution noncommercial|attribution non commercial", r"(?:cc by nc sa|(?:creative commons )?attribution non ?commercial share ?alike)(?: [1-4] [05])?", "cc by nc sa 4 0"),
    ("cc-by-nc", "cc by nc|attribution noncommercial|attribution non commercial", r"(?:cc by nc|(?:creative commons )?attribution non ?commercial)(?: [1-4] [05])?", "cc by nc 4 0"),
    ("cc-by-nd", "cc by nd|attribution no", r"(?:cc by nd|(?:creative commons )?attribution no ?derivatives?)(?: [1-4] [05])?", "cc by nd 4 0"),
    ("cc-by-sa", "cc by sa|attribution share", r"(?:cc by sa|(?:creative commons )?attribution share ?alike)(?: [1-4] [05])?", "cc by sa 4 0"),
    ("cc-by", "cc by|commons attribution", r"(?:cc by|creative commons attribution)(?: [1-4] [05])?", "cc by 4 0"),
    ("cecill-2.1", "cecill", r"cecill(?: license)?(?: version)? v?2 1", "cecill 2 1"),
    ("bzip2", "bzip2", r"bzip2", "bzip2 1 0 6"),
    ("unicode", "unicode", r"unicode(?: inc)?(?: terms of use)?", "unicode 3 0"),
    ("vim", "vim", r"vim", "vim"),
    ("elastic-2", "elastic", r"elastic(?: license)?(?: version)? 2(?: 0)?", "elastic 2 0"),
    ("sspl-1", "sspl|server side public", r"(?:sspl|server side public)(?: license)?(?: version)? v?1(?: 0)?", "sspl 1 0"),
]
# How a name is stated, with its priority (less is better) and confidence.
FORMS = [
    (1, 0.99, r"spdx license identifier {tag}(?: only| or later)?"),
    (2, 0.95, r"licensed under (?:the )?(?:terms of )?(?:the )?(?:{name})(?: license)?"),
    (2, 0.95, r"(?:released|distributed|available|provided|published|shared) under (?:the )?(?:terms of )?(?:the )?(?:{name})(?: license)?"),
    (3, 0.9, r"under the terms (?:and conditions )?of (?:the )?(?:{name})(?: license)?"),
    (4, 0.8, r"licen[cs]e (?:is )?(?:the )?(?:{name})(?: license)?"),
    (5, 0.7, r"(?:{name}) licen[cs]ed?"),
]
# Signatures of license texts.
TEXTS = [
    ("0bsd", "permission to use copy", r"permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted(?! provided)"),
    ("mit", "permission is hereby", r"permission is hereby granted free of charge to any person obtaining a copy of this software"),
    ("isc", "permission to use", r"permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    ("bsd-3", "redistribution and use", r"redistribution and use in source and binary forms .{0,900}neither the name"),
    ("bsd-4", "redistribution and use", r"redistribution and use in source and binary forms .{0,900}all advertising materials"),
    ("bsd-2", "redistribution and use", r"redistribution and use in source and binary forms with or without modification are permitted"),
    ("apache-2", "you may not use this file", r"you may not use this file except in compliance with the license"),
    ("gpl-3", "free software", r"this program is free software you can redistribute it .{0,120}either version 3 of the license"),
    ("gpl-2", "free software", r"this program is free software you can redistribute it .{0,120}either version 2 of the license"),
    ("mpl-2", "source code form", r"this source code form is subject to the terms of the mozilla public license"),
    ("zlib", "as is", r"this software is provided as is without any express or implied warranty in no event will the authors"),
    ("bsl-1", "permission is hereby", r"permission is hereby granted free of charge to any person or organization obtaining a copy"),
    ("wtfpl", "everyone is permitted", r"everyone is permitted to copy and distribute verbatim or modified copies of this license document"),
    ("unlicense", "public domain", r"this is free and unencumbered software released into the public domain"),
    ("cc0-1", "public domain", r"dedicated (?:this|the) (?:work|software|person).{0,80}to the public domain"),
    ("public-domain", "public domain", r"(?:released|placed|dedicated|donated) (?:in)?to the public domain"),
    ("mit-0", "without restriction including", r"permission is hereby granted free of charge .{0,160}deal in the software without restriction including .{0,200}to permit persons to whom the software is furnished to do so(?! subject)"),
    ("mit", "this permission notice shall be", r"(?:above|this) copyright notice and this permission notice shall be included in all copies"),
    ("x11", "the x consortium", r"except as contained in this notice the name of the x consortium shall not be used .{0,120}without prior written (?:authorization|permission)"),
    ("mit-advertising", "shall not be used in advertising", r"the names? of .{1,120}shall not be used in advertising or otherwise to promote .{0,120}without prior written (?:authorization|permission)"),
    ("hpnd", "permission to use copy", r"permission to use copy modify and distribute this software and its documentation for any purpose (?:and )?without fee is hereby granted"),
    ("ntp", "permission to use copy", r"permission to use copy modify and distribute this software and its documentation for any purpose with or without fee is hereby granted"),
    ("isc", "permission to use copy", r"permission to use copy modify and distribute this software for any purpose with or without fee is hereby granted"),
    ("bsd-2", "list of conditions", r"redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer"),
    ("bsd-3", "endorse or promote", r"(?:names? of|contributors) .{0,120}may (?:not )?be used to endorse or promote products derived from this software without specific prior written permission"),
    ("bsd-4", "all advertising materials", r"all advertising materials mentioning features or use of this software must display the following acknowledge?ment .{0,600}permission"),
    ("bsd-clear", "no express or implied licenses", r"no express or implied licenses to any party s patent rights are granted by this license"),
    ("apache-2", "apache license", r"licensed under the apache license version 2 0 (?:the license)? ?you may not use"),
    ("apache-2", "on an as is basis", r"software distributed under the license is distributed on an as is basis without warranties or conditions of any kind"),
    ("apache-1.1", "apache software foundation", r"this product includes software developed by the apache software foundation .{0,400}permission"),
    ("apache-1", "apache group", r"this product includes software developed by the apache group .{0,400}permission"),
    ("gpl-2-or-later", "either version 2", r"general public license as published by the free software foundation either version 2 of the license or at your option any later version"),
    ("gpl-3-or-later", "either version 3", r"general public license as published by the free software foundation either version 3 of the license or at your option any later version"),
    ("gpl-2-only", "general public license", r"under the terms of the gnu general public license (?:as published by the free software foundation )?version 2 (?:only|of the license only)"),
    ("lgpl-2.1-or-later", "lesser general public", r"lesser general public license as published by the free software foundation either version 2 1 of the license or at your option any later version"),
    ("lgpl-3-or-later", "lesser general public", r"lesser general public license as published by the free software foundation either version 3 of the license or at your option any later version"),
    ("lgpl-2-or-later", "library general public", r"library general public license as published by the free software foundation either version 2 of the license or at your option any later version"),
    ("agpl-3-or-later", "affero general public", r"affero general public license as published by the free software foundation either version 3 of the license or at your option any later version"),
    ("gpl-warranty", "hope that it will be useful", r"distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose"),
    ("gpl-received", "received a copy of the gnu", r"you should have received a copy of the gnu (?:lesser |library |affero )?general public license along with"),
    ("gfdl", "free documentation license", r"permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation license"),
    ("classpath-exception", "linking this library statically", r"linking this library statically or dynamically with other modules is making a combined work .{0,200}permission"),
    ("mpl-2", "a copy of the mpl was not distributed", r"if a copy of the mpl was not distributed with this file you can obtain one .{0,40}licen[cs]e"),
    ("mpl-1.1", "mozilla public license", r"the contents of this file are subject to the mozilla public license version 1 1"),
    ("mpl-1", "mozilla public license", r"the contents of this file are subject to the mozilla public license version 1 0"),
    ("npl-1.1", "netscape public license", r"the contents of this file are subject to the netscape public license version 1 1"),
    ("cddl-1", "common development and distribution", r"subject to the terms of the common development and distribution license"),
    ("epl-2", "eclipse public license", r"this program and the accompanying materials are made available under the terms of the eclipse public license (?:v |version )?2 0"),
    ("epl-1", "eclipse public license", r"this program and the accompanying materials are made available under the terms of the eclipse public license (?:v |version )?1 0"),
    ("edl-1", "eclipse distribution license", r"this program and the accompanying materials are made available under the terms of the eclipse distribution license"),
    ("cpl-1", "common public license", r"this program and the accompanying materials are made available under the terms of the common public license"),
    ("osl-3", "open software license", r"licensed under the open software license version 3 0"),
    ("afl-3", "academic free license", r"licensed under the academic free license version 3 0"),
    ("artistic-2", "artistic license", r"(?:you may|you can) redistribute it and or modify it under the terms of the (?:the )?artistic license (?:version )?2 0"),
    ("perl", "same terms as perl", r"(?:redistribute|modify|redistribut[^ ]*) .{0,40}under the same terms as perl(?: itself)?"),
    ("zlib", "including commercial applications", r"permission is granted to anyone to use this software for any purpose including commercial applications"),
    ("bsl-1", "boost software license", r"distributed under the boost software license version 1 0"),
    ("unlicense", "copyright interest in the software to the public domain", r"dedicate any and all copyright interest in the software to the public domain"),
    ("cc0-1", "neighboring rights|public domain dedication", r"(?:waived|dedicated) .{0,160}all copyright and related (?:or|and) neighboring rights .{0,200}licen[cs]e|no copyright .{0,200}public domain dedication"),
    ("cc-by-4", "attribution 4 0 international", r"creative commons attribution 4 0 international(?: public)? license"),
    ("cc-by-sa-4", "sharealike 4 0 international", r"creative commons attribution sharealike 4 0 international(?: public)? license"),
    ("cc-by-sa-3", "alike 3 0 unported", r"creative commons attribution share ?alike 3 0 unported license"),
    ("cc-by-3", "attribution 3 0 unported", r"creative commons attribution 3 0 unported license"),
    ("cc-by-nc-sa-4", "noncommercial sharealike 4 0 international", r"creative commons attribution noncommercial sharealike 4 0 international(?: public)? license"),
    ("cc-by-nc-4", "noncommercial 4 0 international", r"creative commons attribution noncommercial 4 0 international(?: public)? license"),
    ("cc-by-nc-nd-4", "noderivatives 4 0 international", r"creative commons attribution noncommercial noderivatives 4 0 international(?: public)? license"),
    ("cc-by-nd-4", "attribution noderivatives 4 0 international", r"creative commons attribution noderivatives 4 0 international(?: public)? license"),
    ("ofl-1.1", "sil open font license", r"this font software is licensed under the sil open font license version 1 1"),
    ("odbl-1", "open database license", r"made available under the open database license"),
    ("odc-by-1", "open data commons attribution license", r"made available under the open data commons attribution license"),
    ("pddl-1", "public domain dedication and license", r"made available under the public domain dedication and license"),
    ("busl-1.1", "change license", r"business source license .{0,400}change date .{0,200}change license"),
    ("elastic-2", "hosted or managed service", r"you may not provide the software to third parties as a hosted or managed service .{0,400}licen[cs]e"),
    ("sspl-1", "server side public license", r"under the terms of the server side public license version 1"),
    ("commons-clause", "commons clause", r"commons clause license condition"),
    ("polyform-noncommercial", "polyform noncommercial", r"polyform noncommercial license"),
    ("polyform-small-business", "polyform small business", r"polyform small business license"),
    ("hippocratic-2", "hippocratic license", r"hippocratic license(?: version)? 2"),
    ("json", "good not evil", r"the software shall be used for good not evil .{0,400}warranty"),
    ("beerware", "beer ware license", r"the beer ware license(?: revision [0-9]+)?"),
    ("wtfpl", "do what the fuck you want to", r"do what the fuck you want to public license"),
    ("openssl", "openssl toolkit", r"this product includes software developed by the openssl project for use in the openssl toolkit .{0,600}permission"),
    ("ssleay", "eric young", r"this product includes cryptographic software written by eric young .{0,900}(?:redistribut|licen[cs]e)"),
    ("curl", "permission to use copy", r"permission to use copy modify and distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice .{0,200}appear in all copies"),
    ("python-2", "python software foundation license", r"python software foundation license version 2"),
    ("php-3", "php software|called php", r"this product includes php software freely available .{0,600}redistribut|redistribution and use in source and binary forms .{0,900}products derived from this software may not be called php"),
    ("ruby", "make and give away verbatim copies", r"you may make and give away verbatim copies of the source form of the software without restriction .{0,400}(?:permission|warranty|domain|redistribut)"),
    ("icu", "unicode data files", r"permission is hereby granted free of charge to any person obtaining a copy of the unicode data files"),
    ("w3c", "w3c software notice", r"w3c software notice and license"),
    ("eupl-1.2", "the eupl|european union public licence", r"licensed under the eupl(?: version)? 1 2|this work is licensed under the european union public licence v ?1 2"),
    ("cecill", "french law", r"cecill licen[cs]e under french law|governed by the cecill[ a-z]{0,3} licen[cs]e under french law"),
    ("mulan-psl-2", "mulan psl v2", r"licensed under mulan psl v2"),
    ("nist-pd", "title 17 section 105", r"pursuant to title 17 section 105 .{0,200}public domain"),
    ("us-government-work", "work of the united states government", r"work of the united states government .{0,200}public domain"),
    ("proprietary-confidential", "confidential and proprietary", r"confidential and proprietary .{0,200}(?:permission|under|licen[cs]e|reserved)"),
    ("proprietary-no-redistribution", "may not be reproduced", r"may not be reproduced (?:or )?(?:distributed |transmitted )?.{0,120}without (?:the )?(?:prior )?(?:express )?written permission"),
    ("noncommercial-use", "non commercial use only", r"(?:licensed|permission|provided under) .{0,120}non commercial use only"),
    ("educational-use", "educational and research purposes", r"permission to .{0,160}for educational and research purposes"),
    ("proprietary", "all rights reserved", r"all rights reserved"),
]
#: Parts of single words, so that no line break or hyphen hides them. Every rule's regex and every base phrase needs one of
#: them, so a text without any holds no detection; each rule's own keyword is tested next, on the joined words.
TRIGGERS = ("licen", "under", "domain", "permission", "redistribut", "reserved", "warranty", "authorization", "cc")


class Rule(NamedTuple):
    label: str
    keywords: tuple[str, ...]
    pattern: re.Pattern
    priority: int
    confidence: float


@lru_cache(1)
def rules() -> list[Rule]:
    """The ordered table: signatures of texts, then every name in every form in which licenses are named."""
    out = [Rule(label, tuple(key.split("|")), re.compile(rf"\b{p}\b"), 0, 0.99) for label, key, p in TEXTS]
    out += [Rule(label, tuple(key.split("|")) if priority > 1 else (f"spdx license identifier {tag}",), re.compile(rf"\b{form.format(name=name, tag=tag)}(?! [0-9] [0-9]\b)\b" if priority > 1 else rf"\b{form.format(name=name, tag=tag)}\b"), priority, conf) for priority, conf, form in FORMS for label, key, name, tag in NAMES]
    return sorted(out, key=lambda r: r.priority)


def detect(text: str) -> list[tuple[int, int, str, float]]:
    """Detections left (start, end, label, confidence) in a lower-case word string."""
    found = []
    for order, r in enumerate(rules()):
        if any(k in text for k in r.keywords):
            found += [(r.priority, m.start() - m.end(), order, m.start(), m.end(), r) for m in r.pattern.finditer(text)]
    kept: list[tuple[int, int, str, float]] = []
    starts, ends = [], []  # of taken detections that lie in no other: both ascend
    for _, _, _, s, e, r in sorted(found, key=lambda f: f[:5]):
        i = bisect_right(starts, s)
        if i and ends[i - 1] >= e:  # of those that start no later, the last reaches furthest
            continue
        kept.append((s, e, r.label, r.confidence))
        lo = bisect_left(starts, s)
        hi = bisect_right(ends, e)
        starts[lo : max(lo, hi)], ends[lo : max(lo, hi)] = [s], [e]  # those inside the new one say no more
    return sorted(kept)


def base_places(tokens: list[str]) -> list[tuple[int, str]]:
    """(first word, label) of every place where a base phrase stands."""
    heads = {p[0] for p in BASE}
    return [(i, label) for i, w in enumerate(tokens) if w in heads for p, label in BASE.items() if tuple(tokens[i : i + len(p)]) == p]


_SEPARATOR = np.zeros(256, bool)
_SEPARATOR[list(range(0x30)) + list(range(0x3A, 0x41)) + list(range(0x5B, 0x61)) + list(range(0x7B, 0x80))] = True


def _word_counts(texts: pa.Array) -> np.ndarray:
    raw, offsets = utf8(texts)
    out = np.zeros(len(texts), np.int64)
    for lo, hi in chunks(offsets):
        out[lo:hi] = np.diff(words(raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo], _SEPARATOR)[2])
    return out


def _scan(batches):
    for batch in batches:
        rows = []
        for value in batch.column(1):
            text = (value.as_py() or "").translate(_LOWER) if value.is_valid else ""
            if not any(t in text for t in TRIGGERS):
                rows.append((0, None, None, [], [], 0.0))
                continue
            tokens = WORD.findall(text)
            places = base_places(tokens)
            found = detect(" ".join(tokens))
            base = sorted({x for _, x in places})
            labels = sorted({*base, *(f[2] for f in found)})
            score = max([0.9] * bool(places) + [f[3] for f in found], default=0.0)
            rows.append((len(places), min((p for p, _ in places), default=None), max((p for p, _ in places), default=None), base, labels, score))
        n, first, last, base, labels, score = zip(*rows, strict=True) if rows else [()] * 6
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(_word_counts(batch.column(1)), pa.int64()), pa.array(n, pa.int64()), pa.array(first, pa.int64()), pa.array(last, pa.int64()), pa.array(base, pa.list_(pa.string())), pa.array(labels, pa.list_(pa.string())), pa.array(score, pa.float64())],
            ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score"])


def scan_licenses(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row for every input row, with label arrays."""
    kind = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels array<string>, labels array<string>, score double"
    return df.select(df[id_col].cast("long").alias("doc_id"), df[text_col].cast("string").alias("text")).mapInArrow(_scan, kind)


def query(spark, sf_dir: str) -> DataFrame:
    out = scan_licenses(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.selectExpr("doc_id", "n_words", "n_base", "first_word", "last_word", "array_join(base_labels, ',') AS base_labels", "array_join(labels, ',') AS labels", "score")
