"""License scans with ordered signature rules, in DataFrame functions alone.

A rule is a regular expression over words (A-Z in lower case, one blank between), with keywords, a label, a priority
and a weight.  Texts without any of the anchors' stems are not looked at further.  In the others every anchor word
(``license``, ``spdx``, ...) gets a window of ``REACH`` words to both sides; a rule is tried where one of its keywords is
in the window, and counts if its match covers the anchor.  Of the detections at an anchor, one whose interval lies within
another's of higher priority (or of the same, and longer; or just as long, and earlier in the rules' order) is
suppressed.  No pattern can match more than ``REACH`` words, so a match and all that could contain it are in the window.
Phrase rules (``base``) are never suppressed.

Patterns are literals of the plan, so each is compiled once a task; rules with the same keywords share one test for them.

Everything happens in the row: no shuffle, no Python.  Cost grows with the words of texts that hold a keyword.

Defined cases: null and empty texts have no words, no detections and score 0; labels are then empty strings; repeated
rows are each scanned; other columns are ignored.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import read

# The words of the task, in a pattern that takes A-Z as well.
WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
REACH = 24
ANCHORS = ["license", "licence", "licensed", "licenses", "spdx", "unlicense", "redistribution", "permission", "copyleft", "domain", "reserved", "warranty", "creativecommons", "wtfpl", "proprietary", "licensing", "sublicense", "redistributions", "warranties", "permissions", "licensor"]
STEMS = ["licen", "spdx", "redistribution", "permission", "copyleft", "domain", "reserved", "warrant", "creativecommons", "wtfpl", "proprietary"]

#: label, the words of its name, the words of its identifier.
FAMILIES = [
    ("mit", "mit license", "mit"),
    ("apache", "apache (?:software )?license", r"apache (?:1 0|1 1|2 0)"),
    ("gpl", "(?:gnu )?general public license", r"gpl (?:1|2|3) 0(?: only| or later)?"),
    ("lgpl", "(?:gnu )?(?:lesser|library) general public license", r"lgpl (?:2|3) (?:0|1)(?: only| or later)?"),
    ("agpl", "(?:gnu )?affero general public license", r"agpl (?:1|3) 0(?: only| or later)?"),
    ("fdl", "(?:gnu )?free documentation license", r"gfdl 1 (?:1|2|3)(?: only| or later)?"),
    ("bsd", r"(?:(?:2|3|4|two|three|four) clause |modified |simplified |new )?bsd(?: (?:2|3|4) clause)? license", r"bsd (?:2|3|4) clause|0bsd"),
    ("mpl", "mozilla public license", r"mpl (?:1 0|1 1|2 0)"),
    ("epl", "eclipse public license", r"epl (?:1|2) 0"),
    ("eupl", "european union public license", r"eupl 1 (?:0|1|2)"),
    ("cddl", "common development and distribution license", r"cddl 1 (?:0|1)"),
    ("cpl", "common public license", "cpl 1 0"),
    ("isc", "isc license", "isc"),
    ("zlib", r"zlib(?: libpng)? license", "zlib"),
    ("boost", "boost software license", "bsl 1 0"),
    ("artistic", "artistic license", r"artistic (?:1|2) 0"),
    ("python", "(?:python software foundation|psf) license", r"(?:psf|python) 2 0"),
    ("unlicense", "unlicense(?: license)?", "unlicense"),
    ("wtfpl", "do what the fuck you want to public license|wtfpl(?: license)?", "wtfpl"),
    ("ms-pl", "microsoft public license", "ms pl"),
    ("ms-rl", "microsoft reciprocal license", "ms rl"),
    ("ofl", "(?:sil )?open font license", r"ofl 1 (?:0|1)"),
    ("odbl", "open database license", "odbl 1 0"),
    ("php", "php license", r"php 3 (?:0|01)"),
    ("ruby", "ruby license", "ruby"),
    ("postgresql", "postgresql license", "postgresql"),
    ("openssl", "openssl license", "openssl"),
    ("academic", "academic free license", r"afl (?:1|2|3) (?:0|1|2)"),
    ("osl", "open software license", r"osl (?:1|2|3) (?:0|1)"),
    ("upl", "universal permissive license", "upl 1 0"),
    ("bsl", "business source license", "busl 1 1"),
    ("sspl", "server side public license", "sspl 1 0"),
    ("elastic", "elastic license", "elastic 2 0"),
    ("apsl", "apple public source license", r"apsl (?:1|2) (?:0|1|2)"),
    ("ipl", "ibm public license", "ipl 1 0"),
    ("npl", "netscape public license", r"npl 1 (?:0|1)"),
    ("spl", "sun public license", "spl 1 0"),
    ("sissl", "sun industry standards source license", r"sissl(?: 1 2)?"),
    ("qpl", "q public license", r"qpl 1 0(?: inria 2004)?"),
    ("lppl", "latex project public license", r"lppl 1 (?:0|1|2|3a|3c)"),
    ("zpl", "zope public license", r"zpl (?:1|2) (?:0|1)"),
    ("w3c", "w3c (?:software (?:notice and )?(?:and document )?)?license", r"w3c(?: 19980720| 20150513)?"),
    ("x11", "x11 license", "x11"),
    ("ncsa", r"(?:university of illinois )?ncsa open source license", "ncsa"),
    ("ecl", "educational community license", r"ecl (?:1|2) 0"),
    ("cecill", r"cecill(?: b| c)?(?: free software)? license(?: agreement)?", r"cecill (?:1 0|1 1|2 0|2 1|b|c)"),
    ("rpl", "reciprocal public license", r"rpl 1 (?:1|5)"),
    ("nposl", "non profit open software license", "nposl 3 0"),
    ("eudatagrid", "eu datagrid software license", "eudatagrid"),
    ("vim", "vim license", "vim"),
    ("tcl", "tcl tk license", "tcl"),
    ("curl", "curl license", "curl"),
    ("icu", r"icu license|unicode license agreement", "icu"),
    ("libpng", r"(?:libpng|png reference library) license(?: version 2)?", r"libpng(?: 2 0)?"),
    ("ijg", "independent jpeg group license", "ijg"),
    ("freetype", r"freetype (?:project )?license", "ftl"),
    ("imagemagick", "imagemagick license", "imagemagick"),
    ("mulan", r"mulan (?:permissive software|psl) license", r"mulanpsl (?:1|2) 0"),
    ("ncgl", "non commercial government licence", "ncgl uk 2 0"),
    ("ogl", "open government licence", r"ogl (?:uk|canada) (?:1|2|3) 0"),
    ("pddl", "public domain dedication and license", "pddl 1 0"),
    ("odc-by", "open data commons attribution license", "odc by 1 0"),
    ("polyform-nc", "polyform noncommercial license", "polyform noncommercial 1 0 0"),
    ("polyform-sb", "polyform small business license", "polyform small business 1 0 0"),
    ("beerware", "beer ?ware license", "beerware"),
    ("llama-community", r"llama (?:\d )?(?:\d )?community license(?: agreement)?", r"llama ?(?:\d )?community"),
    ("openrail", r"(?:creativeml |bigscience )?(?:bloom )?open ?rail(?: m)? license", r"openrail(?: m)?"),
    ("cc0", r"(?:cc0|creative commons zero)(?: 1 0)?(?: universal)?(?: license)?", "cc0 1 0"),
    ("cc-by", r"(?:cc by|creative commons attribution)(?: (?:2 0|2 5|3 0|4 0))(?: international| unported)?(?: license)?", r"cc by (?:1 0|2 0|2 5|3 0|4 0)"),
    ("cc-by-sa", r"(?:cc by sa|creative commons attribution share ?alike)(?: (?:2 0|2 5|3 0|4 0))?(?: international| unported)?(?: license)?", r"cc by sa (?:1 0|2 0|2 5|3 0|4 0)"),
    ("cc-by-nd", r"(?:cc by nd|creative commons attribution no ?derivatives)(?: (?:2 0|2 5|3 0|4 0))?(?: international| unported)?(?: license)?", r"cc by nd (?:1 0|2 0|2 5|3 0|4 0)"),
    ("cc-by-nc", r"(?:cc by nc|creative commons attribution non ?commercial)(?: (?:2 0|2 5|3 0|4 0))?(?: international| unported)?(?: license)?", r"cc by nc (?:1 0|2 0|2 5|3 0|4 0)"),
    ("cc-by-nc-sa", r"(?:cc by nc sa|creative commons attribution non ?commercial share ?alike)(?: (?:2 0|2 5|3 0|4 0))?(?: international| unported)?(?: license)?", r"cc by nc sa (?:1 0|2 0|2 5|3 0|4 0)"),
    ("cc-by-nc-nd", r"(?:cc by nc nd|creative commons attribution non ?commercial no ?derivatives)(?: (?:2 0|2 5|3 0|4 0))?(?: international| unported)?(?: license)?", r"cc by nc nd (?:1 0|2 0|2 5|3 0|4 0)"),
]
VERSION = r"(?: v ?\d+| version \d+)?(?: \d+)?(?: or later| or any later version| only)?"
#: What stands around a name: before it, after it, priority, weight.
PHRASES = [
    ("", "", 1, 0.6),
    ("", VERSION, 2, 0.7),
    (r"(?:is |are |be )?licensed (?:to you )?(?:under|with) (?:the |an? )?(?:terms of (?:the )?)?", VERSION, 4, 0.95),
    (r"(?:re)?(?:released|published|distributed|available|provided) under (?:the |an? )?(?:terms of (?:the )?)?", VERSION, 4, 0.9),
    (r"(?:subject to|covered by|governed by|under) (?:the |an? )?(?:terms (?:and conditions )?of (?:the )?)?", VERSION, 3, 0.8),
]
#: Sentences and notices that stand for a license without a name in a frame: keywords (a match holds one of them), pattern, label, priority, weight.
SIGNATURES = [
    ("hereby", "permission is hereby granted free of charge to any person obtaining a copy", "mit", 5, 0.95),
    ("sublicense", "to use copy modify merge publish distribute sublicense and or sell copies of the software", "mit", 5, 0.95),
    ("notice", "this permission notice shall be included in all copies or substantial portions of the software", "mit", 5, 0.9),
    ("expat", "expat license", "mit", 4, 0.9),
    ("x11", "mit x11 license", "mit", 4, 0.9),
    ("attribution", "mit no attribution license", "mit-0", 4, 0.9),
    ("mit", "(?:the )?license (?:is|type|name) mit", "mit", 3, 0.8),
    ("mit", "mit style license", "mit", 2, 0.7),
    ("purpose", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "isc", 5, 0.95),
    ("purpose", "permission to use copy modify and distribute this software for any purpose with or without fee is hereby granted", "isc", 5, 0.9),
    ("documentation", "permission to use copy modify (?:and )?distribute and sell this software and its documentation for any purpose", "hpnd", 5, 0.9),
    ("documentation", "permission to use copy modify and distribute this software and its documentation for any purpose", "hpnd", 5, 0.9),
    ("binary", "redistribution and use in source and binary forms with or without modification are permitted", "bsd", 5, 0.95),
    ("retain", "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer", "bsd", 5, 0.95),
    ("reproduce", "redistributions in binary form must reproduce the above copyright notice", "bsd", 5, 0.95),
    ("endorse", "endorse or promote products derived from this software without specific prior written permission", "bsd", 5, 0.9),
    ("bsd", "bsd style license", "bsd", 2, 0.7),
    ("bsd", r"(?:dual )?licensed (?:under )?(?:the )?(?:new |modified )?bsd(?: or gpl)?", "bsd", 4, 0.8),
    ("regents", "this software is provided by the regents and contributors as is and any express or implied warranties", "bsd", 4, 0.8),
    ("apache", r"licensed under the apache license version 2 0 the license", "apache", 6, 1.0),
    ("apache", r"apache org licenses license 2 0", "apache", 6, 1.0),
    ("apache", r"apache license version (?:1 0|1 1|2 0)", "apache", 5, 0.95),
    ("compliance", "you may not use this file except in compliance with the license", "apache", 5, 0.8),
    ("agreed", "unless required by applicable law or agreed to in writing software distributed under the license", "apache", 5, 0.8),
    ("governing", "see the license for the specific language governing permissions and limitations", "apache", 5, 0.8),
    ("contributor", "licensed to the apache software foundation asf under one or more contributor license agreements", "apache", 6, 1.0),
    ("asl", r"asl (?:1 1|2 0) license", "apache", 4, 0.8),
    ("redistribute", "redistribute it and or modify it under the terms of the gnu general public license", "gpl", 6, 1.0),
    ("redistribute", "redistribute it and or modify it under the terms of the gnu (?:lesser|library) general public license", "lgpl", 6, 1.0),
    ("redistribute", "redistribute it and or modify it under the terms of the gnu affero general public license", "agpl", 6, 1.0),
    ("foundation", "as published by the free software foundation either version (?:1|2|2 1|3) of the license", "gpl-family", 5, 0.9),
    ("later", "of the license or at your option any later version", "gpl-family", 3, 0.7),
    ("received", "you should have received a copy of the gnu general public license", "gpl", 5, 0.95),
    ("received", "you should have received a copy of the gnu (?:lesser|library) general public license", "lgpl", 5, 0.95),
    ("received", "you should have received a copy of the gnu affero general public license", "agpl", 5, 0.95),
    ("gnu", r"gnu org licenses gpl(?: \d 0)?(?: html| txt)?", "gpl", 5, 0.95),
    ("gnu", r"gnu org licenses lgpl(?: \d (?:0|1))?(?: html| txt)?", "lgpl", 5, 0.95),
    ("gnu", r"gnu org licenses agpl(?: \d 0)?(?: html| txt)?", "agpl", 5, 0.95),
    ("gnu", r"gnu org licenses fdl(?: 1 \d)?(?: html| txt)?", "fdl", 5, 0.95),
    ("gpl", r"licensed under (?:the )?(?:gnu )?gpl(?: ?v? ?(?:1|2|3))?(?: 0)?(?: or later| only)?", "gpl", 4, 0.9),
    ("gpl", r"gpl ?v?(?:1|2|3)?(?: 0)? license", "gpl", 3, 0.8),
    ("lgpl", r"licensed under (?:the )?(?:gnu )?lgpl(?: ?v? ?(?:2|3))?(?: (?:0|1))?(?: or later| only)?", "lgpl", 4, 0.9),
    ("lgpl", r"lgpl ?v?(?:2|3)?(?: (?:0|1))? license", "lgpl", 3, 0.8),
    ("agpl", r"licensed under (?:the )?(?:gnu )?agpl(?: ?v? ?3)?(?: 0)?(?: or later| only)?", "agpl", 4, 0.9),
    ("agpl", r"agpl ?v?3?(?: 0)? license", "agpl", 3, 0.8),
    ("classpath", "general public license (?:version 2 )?with (?:the )?classpath exception", "gpl-classpath", 6, 0.95),
    ("linking", "general public license (?:version 2 )?with (?:a |the )?linking exception", "gpl-linking", 6, 0.95),
    ("fitness", "without even the implied warranty of merchantability or fitness for a particular purpose", "gpl-family", 3, 0.5),
    ("invariant", "free documentation license (?:version )?1 (?:1|2|3) or any later version published by the free software foundation with no invariant sections", "fdl", 6, 1.0),
    ("mozilla", "this source code form is subject to the terms of the mozilla public license", "mpl", 6, 1.0),
    ("mpl", r"the license at https? mozilla org mpl(?: 2 0)?|licensed under (?:the )?mpl", "mpl", 4, 0.9),
    ("incompatible", "this source code form is incompatible with secondary licenses", "mpl-no-copyleft", 6, 1.0),
    ("contents", "the contents of this file are subject to the (?:mozilla|netscape) public license", "mpl", 6, 1.0),
    ("tri", "mpl 1 1 gpl 2 0 lgpl 2 1 tri license", "mpl", 4, 0.9),
    ("eclipse", "are made available under the terms of the eclipse public license", "epl", 5, 0.95),
    ("distribution", "eclipse distribution license(?: 1 0| v 1 0)?", "edl", 5, 0.95),
    ("development", r"(?:subject to|under) the terms of the common development and distribution license", "cddl", 6, 1.0),
    ("glassfish", r"glassfish (?:dev java net public )?cddl(?: gpl)?(?: 1 1)? license", "cddl", 5, 0.9),
    ("boost", r"distributed under the boost software license version 1 0", "boost", 6, 1.0),
    ("boost", r"boost org license 1 0(?: txt)?", "boost", 6, 1.0),
    ("organization", "permission is hereby granted free of charge to any person or organization obtaining a copy", "boost", 5, 0.95),
    ("held", "without any express or implied warranty in no event will the authors be held liable", "zlib", 4, 0.8),
    ("anyone", "permission is granted to anyone to use this software for any purpose", "zlib", 5, 0.95),
    ("everyone", "everyone is permitted to copy and distribute verbatim or modified copies of this license document", "wtfpl", 5, 0.9),
    ("everyone", "everyone is permitted to copy and distribute verbatim copies of this license document but changing it is not allowed", "gpl-family", 5, 0.9),
    ("unencumbered", "free and unencumbered software released into the public domain", "unlicense", 6, 1.0),
    ("unlicense", "unlicense org", "unlicense", 4, 0.9),
    ("dedicated", "ha(?:s|ve) dedicated all copyright and related and neighboring rights to this (?:software|work) to the public domain", "cc0", 5, 0.9),
    ("zero", "creativecommons org publicdomain zero 1 0", "cc0", 6, 1.0),
    ("mark", "creativecommons org publicdomain mark 1 0", "public-domain", 6, 1.0),
    ("creativecommons", r"creativecommons org licen[cs]es by \d \d(?: legalcode| deed)?", "cc-by", 6, 1.0),
    ("creativecommons", r"creativecommons org licen[cs]es by sa \d \d(?: legalcode| deed)?", "cc-by-sa", 6, 1.0),
    ("creativecommons", r"creativecommons org licen[cs]es by nd \d \d(?: legalcode| deed)?", "cc-by-nd", 6, 1.0),
    ("creativecommons", r"creativecommons org licen[cs]es by nc \d \d(?: legalcode| deed)?", "cc-by-nc", 6, 1.0),
    ("creativecommons", r"creativecommons org licen[cs]es by nc sa \d \d(?: legalcode| deed)?", "cc-by-nc-sa", 6, 1.0),
    ("creativecommons", r"creativecommons org licen[cs]es by nc nd \d \d(?: legalcode| deed)?", "cc-by-nc-nd", 6, 1.0),
    ("creativecommons", r"creativecommons org licen[cs]es(?: [a-z]{2,8}){0,4}", "cc", 3, 0.7),
    ("commons", "(?:this work is |is )?licensed under a creative commons", "cc", 3, 0.8),
    ("commons", "creative commons license", "cc", 2, 0.7),
    ("commons", "some rights reserved creative commons|creative commons some rights reserved", "cc", 2, 0.7),
    ("domain", r"(?:released |placed |dedicated )?(?:in ?to |in |to )the public domain", "public-domain", 3, 0.8),
    ("domain", "public domain dedication", "public-domain", 3, 0.8),
    ("domain", "(?:this (?:file|work|code|text) is )public domain", "public-domain", 3, 0.8),
    ("domain", "no copyright (?:is )?claimed public domain", "public-domain", 3, 0.7),
    ("government", "work of the (?:united states|u s|us) government (?:and )?(?:is )?(?:therefore )?(?:in )?the public domain", "public-domain-us", 5, 0.9),
    ("reserved", "all rights reserved", "all-rights-reserved", 2, 0.5),
    ("reserved", r"copyright (?:c )?\d{4}(?: \d{4})?(?: [^ ]+){1,6} all rights reserved", "all-rights-reserved", 3, 0.6),
    ("reserved", "no rights reserved", "cc0", 2, 0.6),
    ("confidential", "proprietary and confidential|confidential and proprietary", "proprietary", 3, 0.8),
    ("proprietary", "proprietary (?:software )?license", "proprietary", 3, 0.8),
    ("trade", "contains (?:proprietary )?trade secrets? (?:and|or) proprietary information", "proprietary", 4, 0.8),
    ("prohibited", "unauthorized (?:copying|use|reproduction|distribution)(?: [^ ]+){0,8} without (?:prior )?(?:written )?permission is (?:strictly )?prohibited", "proprietary", 4, 0.8),
    ("written", "(?:may not be|must not be) (?:reproduced|copied|distributed|used)(?: [^ ]+){0,8} without (?:the )?(?:prior )?(?:express )?written permission", "proprietary", 4, 0.8),
    ("user", "end user (?:license|licence) agreement", "eula", 4, 0.8),
    ("evaluation", "evaluation (?:only )?license|license for evaluation purposes only", "evaluation", 3, 0.7),
    ("trial", "(?:free )?trial license", "evaluation", 3, 0.7),
    ("site", "site license", "commercial", 2, 0.5),
    ("commercial", "(?<!non )commercial license", "commercial", 3, 0.7),
    ("commercial", "non commercial (?:use only )?license|licensed for non commercial use", "non-commercial", 4, 0.8),
    ("noncommercial", "noncommercial license|licensed for noncommercial use", "non-commercial", 4, 0.8),
    ("academic", "(?:for )?academic (?:use )?(?:only )?license", "academic-use", 3, 0.7),
    ("research", "(?:for )?research (?:use )?(?:only )?license", "research-use", 3, 0.7),
    ("educational", "licensed for educational (?:use|purposes)(?: only)?", "educational-use", 3, 0.7),
    ("personal", "licensed for personal use(?: only)?", "personal-use", 3, 0.7),
    ("royalty", "(?:non exclusive |worldwide |perpetual |irrevocable ){0,4}royalty free (?:copyright |patent )?license", "royalty-free", 2, 0.5),
    ("patent", "(?:grants? (?:you )?)?(?:a |an )?patent license", "patent-grant", 2, 0.5),
    ("dual", "dual licensed|dual licensing|dual license", "dual-license", 2, 0.4),
    ("multi", "multi licensed|multi licensing", "dual-license", 2, 0.4),
    ("source", "source available license", "source-available", 3, 0.7),
    ("open", "open source license", "open-source", 2, 0.5),
    ("free", "free software license", "open-source", 2, 0.5),
    ("osi", "osi approved(?: open source)? license", "open-source", 3, 0.6),
    ("permissive", "permissive (?:free |open source )?(?:software )?license", "permissive", 2, 0.5),
    ("copyleft", "(?:strong |weak )?copyleft(?: license)?", "copyleft", 1, 0.4),
    ("contributor", "contributor license agreement", "cla", 3, 0.6),
    ("hippocratic", r"hippocratic license(?: version)?(?: \d \d)?", "hippocratic", 4, 0.9),
    ("json", "json license", "json", 4, 0.9),
    ("perl", "same terms as perl(?: itself)?(?: [^ ]+){0,3} license|perl artistic license", "perl", 4, 0.9),
    ("anti", "anti 996 license", "anti-996", 4, 0.9),
    ("commons", "commons clause license condition", "commons-clause", 5, 0.95),
    ("change", r"change license(?: apache| gpl| mpl)", "bsl", 4, 0.8),
    ("confluent", "confluent community license", "confluent", 4, 0.9),
    ("timescale", "timescale license", "timescale", 4, 0.9),
    ("redis", "redis source available license", "rsal", 5, 0.95),
    ("intel", "intel simplified software license", "issl", 4, 0.9),
    ("oracle", "oracle (?:binary code|technology network|free use terms and conditions) license", "oracle", 4, 0.9),
    ("nvidia", "nvidia (?:source code|software) license", "nvidia", 4, 0.9),
    ("kind", "without warranty of any kind", "no-warranty", 1, 0.3),
    ("without", "without any warranty", "no-warranty", 1, 0.3),
    ("warranty", "absolutely no warranty", "no-warranty", 1, 0.3),
    ("conditions", "without warranties or conditions of any kind", "no-warranty", 1, 0.3),
    ("implied", "(?:any )?(?:express(?:ed)? or )?implied warranties of merchantability", "no-warranty", 1, 0.3),
    ("spdx", r"spdx license identifier (?:[a-z0-9]+ ){1,4}(?:or|and|with) [a-z0-9]+", "spdx-expression", 5, 0.9),
    ("licenseref", r"spdx license identifier licenseref(?: [a-z0-9]+){1,3}", "spdx-reference", 5, 0.8),
    ("noassertion", "spdx license identifier noassertion", "spdx-none", 5, 0.3),
]
#: The task's own phrases.
BASE = [("mit", "mit license"), ("apache", "apache license"), ("gpl", "general public license")]


def _anchored(pattern: str) -> str:
    """The pattern with a mark allowed before each anchor word, between word borders."""
    for word in ANCHORS:
        pattern = _whole_word(pattern, word)
    return f"(?<![^ ])(?:{pattern})(?![^ ])"


def _whole_word(pattern: str, word: str) -> str:
    out, at = [], 0
    while (k := pattern.find(word, at)) >= 0:
        before, after = pattern[k - 1:k], pattern[k + len(word):k + len(word) + 1]
        out.append(pattern[at:k] + ("@?" if not before.isalpha() and not after.isalpha() else "") + word)
        at = k + len(word)
    return "".join(out) + pattern[at:]


def rules() -> list[tuple[str, str, str, int, float, int]]:
    """(keywords, pattern, label, priority, weight, words back to the start if a base phrase, else -1), in order."""
    out = [("license", _anchored(p), label, 0, 0.6, len(p.split()) - 1) for label, p in BASE]
    for label, name, ident in FAMILIES:
        out += [(keywords(name), _anchored(f"{before}(?:{name}){after}"), label, priority, weight, -1) for before, after, priority, weight in PHRASES]
        out.append(("spdx", _anchored(f"spdx license identifier (?:{ident})"), label, 6, 1.0, -1))
    return out + [(k, _anchored(p), label, priority, weight, -1) for k, p, label, priority, weight in SIGNATURES]


def _outside(pattern: str) -> str:
    """The pattern without its groups and optional letters."""
    before = None
    while pattern != before:
        before, pattern = pattern, re.sub(r"\([^()]*\)(?:[?*]|\{[^}]*\})?", "#", pattern)
    return re.sub(r".\?", "#", pattern)


def keywords(pattern: str) -> str:
    """Words of which each match holds one, with ``|`` between: the longest one outside of all groups, of those that aren't anchors if there are; else of each way of the first group."""

    def longest(p: str) -> str:
        return max(re.findall("[a-z0-9]+", _outside(p)), key=lambda w: (w not in ANCHORS, len(w)), default="")

    ways = pattern.split("|") if "|" in _outside(pattern) else [pattern]
    if not all(map(longest, ways)):
        ways = re.match(r"\(\?:([^()]*)\)", pattern).group(1).split("|")
    return "|".join(sorted(set(map(longest, ways))))


def _sql() -> str:
    """The detections that stay at the anchors of a column ``windows`` (anchor, win), as SQL: quicker to build than thousands of Columns."""
    known, by_keywords = rules(), {}
    for k, (words, pattern, *_) in enumerate(known):
        by_keywords.setdefault(words, []).append(f"named_struct('rule', {k}, 'all', regexp_extract_all(v.win, r'{pattern}', 0))")
    none = "cast(array() as array<struct<rule:int,all:array<string>>>)"
    gates = {words: " or ".join(f"contains(v.win, '{w}')" for w in words.split("|")) for words in by_keywords}
    tried = f"flatten(array({', '.join(f'if({gates[words]}, array({", ".join(of)}), {none})' for words, of in by_keywords.items())}))"
    marked = f"transform({tried}, t -> named_struct('rule', t.rule, 'match', try_element_at(filter(t.all, m -> contains(m, '@')), 1)))"
    column = lambda k, write: f"element_at(array({', '.join(write(r[k]) for r in known)}), d.rule + 1)"
    own = f"'label', {column(2, lambda x: f"'{x}'")}, 'priority', {column(3, str)}, 'weight', {column(4, lambda x: f'{x}D')}, 'back', {column(5, str)}"
    placed = f"transform(filter({marked}, d -> d.match is not null), d -> named_struct({own}, 'from', instr(v.win, d.match), 'size', length(d.match), 'rule', d.rule, 'anchor', v.anchor))"
    within = "e.from <= d.from and e.from + e.size >= d.from + d.size"
    above = "e.priority > d.priority or (e.priority = d.priority and (e.size > d.size or (e.size = d.size and e.rule < d.rule and e.back < 0)))"
    # an array of one binds the detections, so that they are found once
    return f"flatten(transform(windows, v -> flatten(transform(array({placed}), s -> filter(s, d -> d.back >= 0 or not exists(s, e -> {within} and ({above})))))))"


def _window(words: Column, a: Column) -> Column:
    """The words around an anchor, which is marked."""
    start = F.greatest(a - REACH, F.lit(0))
    win = F.concat_ws(" ", F.slice(words, start + 1, a - start), F.concat(F.lit("@"), F.element_at(words, a + 1)), F.slice(words, a + 2, F.lit(REACH)))
    return F.struct(a.alias("anchor"), win.alias("win"))


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_words and the detections (label, priority, weight, back, anchor word) of every document."""
    text = F.coalesce(F.col("text"), F.lit(""))
    lower = F.translate(text, UPPER, LOWER)
    gate = F.coalesce(F.col("text").rlike("(?i)" + "|".join(STEMS)), F.lit(False))
    words = F.when(gate, F.regexp_extract_all(lower, F.lit(WORD), F.lit(0)))
    read_ = docs.select("doc_id", F.regexp_count(text, F.lit(WORD)).cast("long").alias("n_words"), words.alias("words"))
    at = F.filter(F.transform("words", lambda w, i: F.when(w.isin(ANCHORS), i)), lambda i: i.isNotNull())
    windows = read_.select("doc_id", "n_words", "words", at.alias("anchors")).select("doc_id", "n_words", F.transform("anchors", lambda a: _window(F.col("words"), a)).alias("windows"))
    return windows.select("doc_id", "n_words", F.coalesce(F.expr(_sql()), F.array().cast("array<struct<label:string,priority:int,weight:double,back:int,from:int,size:int,rule:int,anchor:int>>")).alias("found"))


def summary(found: DataFrame) -> DataFrame:
    base = found.select("doc_id", "n_words", "found", F.filter("found", lambda d: d["back"] >= 0).alias("base"))
    starts = F.transform("base", lambda d: (d["anchor"] - d["back"]).cast("long"))
    joined = lambda c: F.array_join(F.array_sort(F.array_distinct(F.transform(c, lambda d: d["label"]))), ",")
    return base.select(
        "doc_id", "n_words", F.size("base").cast("long").alias("n_base"), F.array_min(starts).alias("first_word"), F.array_max(starts).alias("last_word"),
        joined("base").alias("base_labels"), joined("found").alias("labels"), F.coalesce(F.array_max(F.transform("found", lambda d: d["weight"])), F.lit(0.0)).alias("score"),
    )


def op2_signature_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``documents``."""
    return summary(scan(read(spark, sf_dir, "documents")))
