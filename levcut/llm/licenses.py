"""License scan by ordered signature rules, in DataFrame functions alone.

Some four hundred rules: hand-written signatures of license texts and notices,
and the ways of granting a license crossed with its names. A rule has a pattern
over the lower-cased text with white space folded to single blanks, a label, a
priority and a confidence. Its keywords are read off the parsed pattern, so every
match holds one of them: the prefilter loses nothing by construction. A document
is looked at only if it holds one of a few gate words, each a part of a keyword.
Detections are intervals of the folded text; one that lies inside an interval of
higher priority, or of the same priority but longer or of an earlier rule, is
suppressed in one sweep over the sorted intervals.

Beside that the base phrases are found as consecutive words, whatever stands
between the words. All work is done within a row, so nothing is shuffled and no
source or group can become hot.

Nulls: a null text counts as empty: no words, no labels, score 0. Very long texts
are scanned whole. Repeated rows give repeated results; empty tables empty ones;
other columns are ignored.
"""

from __future__ import annotations

import json
import re
from functools import cache
from re import _constants as kind
from re import _parser as parser

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levcut.llm.common import text_column

#: Base phrases and labels.
BASE = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}

#: Label, pattern of the name, short identifier.
NAMES = [
    ("mit", r"(?:the )?mit(?: license)?", "mit"),
    ("apache-2.0", r"(?:the )?apache(?: software)? licen[sc]e,? ?(?:version )?(?:v\.? ?)?2(?:\.0)?", "apache-2.0"),
    ("apache-1.1", r"(?:the )?apache(?: software)? licen[sc]e,? ?(?:version )?(?:v\.? ?)?1\.1", "apache-1.1"),
    ("gpl-2.0", r"(?:the )?(?:gnu )?(?:general public licen[sc]e|gpl),? ?(?:version |v\.? ?)2(?:\.0)?", "gpl-2.0"),
    ("gpl-3.0", r"(?:the )?(?:gnu )?(?:general public licen[sc]e|gpl),? ?(?:version |v\.? ?)3(?:\.0)?", "gpl-3.0"),
    ("lgpl-2.1", r"(?:the )?(?:gnu )?(?:lesser general public licen[sc]e|lgpl),? ?(?:version |v\.? ?)2\.1", "lgpl-2.1"),
    ("lgpl-3.0", r"(?:the )?(?:gnu )?(?:lesser general public licen[sc]e|lgpl),? ?(?:version |v\.? ?)3(?:\.0)?", "lgpl-3.0"),
    ("lgpl", r"(?:the )?(?:gnu )?(?:(?:lesser|library) general public licen[sc]e|lgpl)", "lgpl-2.0"),
    ("agpl-3.0", r"(?:the )?(?:gnu )?(?:affero general public licen[sc]e|agpl),? ?(?:(?:version |v\.? ?)3(?:\.0)?)?", "agpl-3.0"),
    ("gfdl", r"(?:the )?gnu free documentation licen[sc]e", "gfdl-1.3"),
    ("bsd-2-clause", r"(?:the )?(?:2-clause|two-clause|simplified|freebsd) bsd(?: licen[sc]e)?|bsd[ -]2[ -]clause(?: licen[sc]e)?", "bsd-2-clause"),
    ("bsd-3-clause", r"(?:the )?(?:3-clause|three-clause|new|revised|modified) bsd(?: licen[sc]e)?|bsd[ -]3[ -]clause(?: licen[sc]e)?", "bsd-3-clause"),
    ("bsd", r"(?:the )?bsd licen[sc]e", "bsd"),
    ("mpl-1.1", r"(?:the )?mozilla public licen[sc]e,? ?(?:version |v\.? ?)1\.1", "mpl-1.1"),
    ("mpl-2.0", r"(?:the )?mozilla public licen[sc]e,? ?(?:(?:version |v\.? ?)2(?:\.0)?)?", "mpl-2.0"),
    ("epl-1.0", r"(?:the )?eclipse public licen[sc]e,? ?(?:version |v\.? ?|- ?v? ?)1(?:\.0)?", "epl-1.0"),
    ("epl-2.0", r"(?:the )?eclipse public licen[sc]e,? ?(?:(?:version |v\.? ?|- ?v? ?)2(?:\.0)?)?", "epl-2.0"),
    ("cddl", r"(?:the )?common development and distribution licen[sc]e", "cddl-1.0"),
    ("cpl", r"(?:the )?common public licen[sc]e", "cpl-1.0"),
    ("isc", r"(?:the )?isc licen[sc]e", "isc"),
    ("zlib", r"(?:the )?zlib(?:/libpng)? licen[sc]e", "zlib"),
    ("boost", r"(?:the )?boost software licen[sc]e", "bsl-1.0"),
    ("artistic", r"(?:the )?artistic licen[sc]e", "artistic-2.0"),
    ("unlicense", r"(?:the )?unlicen[sc]e", "unlicense"),
    ("wtfpl", r"(?:the )?(?:do what the [a-z*]+ you want to public licen[sc]e|wtfpl)", "wtfpl"),
    ("cc0", r"(?:the )?(?:cc0|creative commons zero)(?:[ -]1\.0)?(?: universal)?", "cc0-1.0"),
    ("cc-by", r"(?:the )?(?:cc[ -]by|creative commons attribution)(?:[ -][1-4]\.0)?", "cc-by-4.0"),
    ("cc-by-sa", r"(?:the )?(?:cc[ -]by-sa|creative commons attribution[ -]share-?alike)(?:[ -][1-4]\.0)?", "cc-by-sa-4.0"),
    ("cc-by-nd", r"(?:the )?(?:cc[ -]by-nd|creative commons attribution[ -]noderiv(?:ative)?s)(?:[ -][1-4]\.0)?", "cc-by-nd-4.0"),
    ("cc-by-nc", r"(?:the )?(?:cc[ -]by-nc|creative commons attribution[ -]noncommercial)(?:[ -][1-4]\.0)?", "cc-by-nc-4.0"),
    ("cc-by-nc-sa", r"(?:the )?(?:cc[ -]by-nc-sa|creative commons attribution[ -]noncommercial[ -]share-?alike)(?:[ -][1-4]\.0)?", "cc-by-nc-sa-4.0"),
    ("cc-by-nc-nd", r"(?:the )?(?:cc[ -]by-nc-nd|creative commons attribution[ -]noncommercial[ -]noderiv(?:ative)?s)(?:[ -][1-4]\.0)?", "cc-by-nc-nd-4.0"),
    ("ofl", r"(?:the )?sil open font licen[sc]e", "ofl-1.1"),
    ("python", r"(?:the )?(?:python software foundation|psf) licen[sc]e", "python-2.0"),
    ("eupl", r"(?:the )?european union public licen[sc]e", "eupl-1.2"),
    ("odbl", r"(?:the )?open (?:data commons open )?database licen[sc]e", "odbl-1.0"),
    ("postgresql", r"(?:the )?postgresql licen[sc]e", "postgresql"),
    ("openssl", r"(?:the )?openssl licen[sc]e", "openssl"),
    ("ms-pl", r"(?:the )?microsoft public licen[sc]e", "ms-pl"),
    ("afl", r"(?:the )?academic free licen[sc]e", "afl-3.0"),
    ("osl", r"(?:the )?open software licen[sc]e", "osl-3.0"),
    ("upl", r"(?:the )?universal permissive licen[sc]e", "upl-1.0"),
]

#: How a license is granted; {n} is its name. Priority, confidence.
GRANTS = [
    (r"(?:re)?licen[sc]ed under {n}", 30, 1.0),
    (r"(?:re)?distributed under (?:the terms of )?{n}", 30, 1.0),
    (r"(?:released|published|available|provided|made available) under (?:the terms of )?{n}", 30, 1.0),
    (r"(?:subject to|governed by|covered by|under) the (?:terms|conditions|terms and conditions) (?:of|in) {n}", 30, 0.95),
    (r"licen[sc]es?(?: type)?: ?{n}", 30, 0.95),
    (r"\b{n}(?: for (?:more )?details)?", 10, 0.8),
]

#: Signatures of license texts and notices: label, pattern, priority, confidence.
SIGNATURES = [
    ("unlicense", r"this is free and unencumbered software released into the public domain", 45, 1.0),
    ("unlicense", r"anyone is free to copy, modify, publish, use, compile, sell,? or distribute this software", 45, 1.0),
    ("unlicense", r"in jurisdictions that recognize copyright laws, the authors? or authors? of this software dedicate", 45, 1.0),
    ("mit", r"permission is hereby granted, free of charge, to any person obtaining a copy", 40, 1.0),
    ("mit", r"to deal in the software without restriction, including without limitation the rights", 40, 1.0),
    ("mit", r"the above copyright notice and this permission notice shall be included in all copies", 40, 1.0),
    ("mit", r"the software is provided [\"']?as is[\"']?, without warranty of any kind, express or implied", 38, 0.9),
    ("mit", r"in no event shall the authors or copyright holders be liable for any claim, damages or other liability", 38, 0.9),
    ("mit-0", r"mit no attribution|mit-0(?![\w-])", 42, 1.0),
    ("x11", r"\bx11 licen[sc]e", 32, 0.95),
    ("x11", r"except as contained in this notice, the name of the x consortium shall not be used", 45, 1.0),
    ("expat", r"\bexpat licen[sc]e", 32, 0.95),
    ("isc", r"permission to use, copy, modify,? and(?:/or)? distribute this software for any purpose", 40, 1.0),
    ("isc", r"the software is provided [\"']?as is[\"']? and the author disclaims all warranties", 40, 1.0),
    ("isc", r"resulting from loss of use, data or profits, whether in an action of contract, negligence", 36, 0.9),
    ("0bsd", r"zero[- ]clause bsd|bsd zero clause|\b0bsd(?![\w-])", 42, 1.0),
    ("bsd", r"redistribution and use in source and binary forms,? with or without modification", 40, 1.0),
    ("bsd", r"redistributions of source code must retain the above copyright notice", 39, 0.95),
    ("bsd", r"redistributions in binary form must reproduce the above copyright notice", 39, 0.95),
    ("bsd", r"this software is provided by the (?:copyright holders and contributors|regents and contributors|authors?) [\"'`]*as is", 39, 0.95),
    ("bsd-3-clause", r"neither the names? of .{1,80}? nor the names of (?:its|their|any) contributors may be used to endorse", 41, 1.0),
    ("bsd-4-clause", r"all advertising materials mentioning features or use of this software must display", 42, 1.0),
    ("bsd-4-clause", r"(?:4-clause|four-clause|original|old) bsd(?: licen[sc]e)?", 32, 0.95),
    ("bsd-protection", r"bsd protection licen[sc]e", 32, 0.95),
    ("apache-2.0", r"licen[sc]ed under the apache licen[sc]e, version 2\.0 \(the [\"']?licen[sc]e[\"']?\)", 45, 1.0),
    ("apache-2.0", r"you may not use this file except in compliance with the licen[sc]e", 41, 0.95),
    ("apache-2.0", r"apache\.org/licenses/license-2\.0", 42, 1.0),
    ("apache-2.0", r"terms and conditions for use, reproduction, and distribution", 38, 0.9),
    ("apache-2.0", r"unless required by applicable law or agreed to in writing, software distributed under the licen[sc]e", 40, 0.95),
    ("apache-1.1", r"this product includes software developed by the apache software foundation", 38, 0.9),
    ("apache-1.0", r"apache licen[sc]e,? (?:version )?1\.0", 32, 0.95),
    ("gpl", r"this program is free software[;:,] you can redistribute it and/or modify it", 40, 0.95),
    ("gpl", r"this program is distributed in the hope that it will be useful, but without any warranty", 40, 0.95),
    ("gpl", r"you should have received a copy of the gnu general public licen[sc]e", 40, 0.95),
    ("gpl", r"the gnu general public licen[sc]e is a free, copyleft licen[sc]e", 41, 1.0),
    ("gpl", r"gnu\.org/licenses/(?:old-licenses/)?gpl", 40, 0.95),
    ("gpl-2.0", r"gnu general public licen[sc]e,? version 2, june 1991", 45, 1.0),
    ("gpl-3.0", r"gnu general public licen[sc]e,? version 3, 29 june 2007", 45, 1.0),
    ("gpl-1.0", r"(?:gnu )?(?:general public licen[sc]e|gpl),? (?:version |v\.? ?)1(?:\.0)?(?![\w.-])", 32, 0.95),
    ("gpl-2.0-or-later", r"either version 2 of the licen[sc]e, or \(at your option\) any later version", 41, 1.0),
    ("gpl-3.0-or-later", r"either version 3 of the licen[sc]e, or \(at your option\) any later version", 41, 1.0),
    ("gpl-2.0-or-later", r"\bgpl-?v?2\+|gplv2 or later", 36, 0.95),
    ("gpl-3.0-or-later", r"\bgpl-?v?3\+|gplv3 or later", 36, 0.95),
    ("gpl-classpath", r"classpath exception", 36, 0.9),
    ("gpl-linking", r"as a special exception, .{0,60}? permission to link", 36, 0.9),
    ("gpl-font", r"font exception", 30, 0.7),
    ("lgpl", r"this library is free software[;:,] you can redistribute it and/or modify it", 40, 0.95),
    ("lgpl", r"you should have received a copy of the gnu lesser general public licen[sc]e", 40, 0.95),
    ("lgpl", r"gnu\.org/licenses/(?:old-licenses/)?lgpl", 40, 0.95),
    ("lgpl-2.0", r"gnu library general public licen[sc]e,? (?:version |v)2(?![.\d])", 41, 1.0),
    ("lgpl-2.1", r"gnu lesser general public licen[sc]e,? version 2\.1, february 1999", 45, 1.0),
    ("lgpl-2.1-or-later", r"either version 2\.1 of the licen[sc]e, or \(at your option\) any later version", 42, 1.0),
    ("agpl-3.0", r"gnu affero general public licen[sc]e is a free, copyleft", 42, 1.0),
    ("agpl-3.0", r"you should have received a copy of the gnu affero general public licen[sc]e", 41, 1.0),
    ("agpl-3.0", r"gnu\.org/licenses/agpl", 41, 1.0),
    ("agpl-1.0", r"affero general public licen[sc]e,? (?:version |v)1", 42, 1.0),
    ("gfdl", r"permission is granted to copy, distribute and/or modify this document under the terms of the gnu free documentation", 42, 1.0),
    ("gfdl", r"with no invariant sections, no front-cover texts", 41, 0.95),
    ("mpl-2.0", r"this source code form is subject to the terms of the mozilla public licen[sc]e, v\. 2\.0", 45, 1.0),
    ("mpl-2.0", r"mozilla\.org/mpl/2\.0", 42, 1.0),
    ("mpl-1.1", r"the contents of this file are subject to the mozilla public licen[sc]e version 1\.1", 45, 1.0),
    ("mpl-1.0", r"mozilla public licen[sc]e,? (?:version |v)1\.0", 32, 0.95),
    ("npl", r"netscape public licen[sc]e", 32, 0.95),
    ("epl-1.0", r"eclipse\.org/legal/epl-v10", 42, 1.0),
    ("epl-2.0", r"eclipse\.org/legal/epl-(?:2\.0|v20)", 42, 1.0),
    ("epl-2.0", r"this program and the accompanying materials are made available under the terms of the eclipse public licen[sc]e", 41, 0.95),
    ("edl-1.0", r"eclipse distribution licen[sc]e", 32, 0.95),
    ("cddl", r"the contents of this file are subject to the terms of the common development and distribution licen[sc]e", 45, 1.0),
    ("cddl", r"opensource\.org/licenses/cddl", 42, 1.0),
    ("cpl", r"the accompanying program is provided under the terms of this common public licen[sc]e", 45, 1.0),
    ("ipl", r"ibm public licen[sc]e", 32, 0.95),
    ("zlib", r"this software is provided 'as-is', without any express or implied warranty", 40, 1.0),
    ("zlib", r"altered source versions must be plainly marked as such", 40, 1.0),
    ("zlib", r"the origin of this software must not be misrepresented", 40, 1.0),
    ("libpng", r"libpng licen[sc]e|png reference library version", 32, 0.95),
    ("boost", r"permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation", 45, 1.0),
    ("boost", r"boost\.org/license_1_0", 42, 1.0),
    ("artistic", r"the intent of this document is to state the conditions under which a package may be copied", 42, 1.0),
    ("artistic", r"under the same terms as perl itself", 40, 0.95),
    ("clarified-artistic", r"clarified artistic licen[sc]e", 33, 0.95),
    ("wtfpl", r"everyone is permitted to copy and distribute verbatim or modified copies of this license document, and changing it is allowed", 42, 1.0),
    ("beerware", r"beer-?ware licen[sc]e|you can buy me a beer in return", 42, 1.0),
    ("cc0", r"creativecommons\.org/publicdomain/zero", 45, 1.0),
    ("cc0", r"waived all copyright and related or neighboring rights", 42, 1.0),
    ("cc-pdm", r"creativecommons\.org/publicdomain/mark", 45, 1.0),
    ("cc-by", r"creativecommons\.org/licenses/by/", 45, 1.0),
    ("cc-by-sa", r"creativecommons\.org/licenses/by-sa/", 45, 1.0),
    ("cc-by-nd", r"creativecommons\.org/licenses/by-nd/", 45, 1.0),
    ("cc-by-nc", r"creativecommons\.org/licenses/by-nc/", 45, 1.0),
    ("cc-by-nc-sa", r"creativecommons\.org/licenses/by-nc-sa/", 45, 1.0),
    ("cc-by-nc-nd", r"creativecommons\.org/licenses/by-nc-nd/", 45, 1.0),
    ("cc-sampling", r"creativecommons\.org/licenses/sampling", 45, 1.0),
    ("ofl", r"scripts\.sil\.org/ofl|openfontlicense\.org", 42, 1.0),
    ("ofl", r"the font software may be sold as part of a larger software package", 42, 1.0),
    ("bitstream-vera", r"bitstream vera fonts? copyright|bitstream vera is a trademark", 42, 1.0),
    ("ubuntu-font", r"ubuntu font licen[sc]e", 32, 0.95),
    ("python", r"python software foundation licen[sc]e version 2", 41, 1.0),
    ("python", r"this licen[sc]e agreement is between the python software foundation", 45, 1.0),
    ("cnri", r"cnri (?:open source )?licen[sc]e agreement", 40, 1.0),
    ("eupl", r"licen[sc]ed under the eupl", 41, 1.0),
    ("odbl", r"opendatacommons\.org/licenses/odbl", 42, 1.0),
    ("odc-by", r"open data commons attribution licen[sc]e|opendatacommons\.org/licenses/by", 42, 1.0),
    ("pddl", r"public domain dedication and licen[sc]e|opendatacommons\.org/licenses/pddl", 42, 1.0),
    ("cdla", r"community data licen[sc]e agreement", 40, 1.0),
    ("ogl", r"open government licen[sc]e", 32, 0.95),
    ("ogl-rpg", r"open game licen[sc]e", 32, 0.95),
    ("postgresql", r"permission to use, copy, modify, and distribute this software and its documentation for any purpose, without fee", 42, 1.0),
    ("ntp", r"is hereby granted, provided that the above copyright notice appears? in all copies", 36, 0.8),
    ("openssl", r"this product includes software developed by the openssl project", 42, 1.0),
    ("ssleay", r"this product includes cryptographic software written by eric young", 42, 1.0),
    ("php", r"\bphp licen[sc]e|this product includes php software", 40, 0.95),
    ("ruby", r"\bruby licen[sc]e|under the same terms as ruby", 40, 0.95),
    ("tcl", r"tcl/tk licen[sc]e", 32, 0.95),
    ("vim", r"\bvim licen[sc]e", 32, 0.95),
    ("w3c", r"w3c software (?:notice and|and document) licen[sc]e", 40, 1.0),
    ("unicode", r"unicode(?:, inc\.)? licen[sc]e agreement", 40, 1.0),
    ("icu", r"\bicu licen[sc]e", 32, 0.95),
    ("curl", r"\bcurl licen[sc]e", 32, 0.95),
    ("ijg", r"based in part on the work of the independent jpeg group", 40, 1.0),
    ("freetype", r"freetype (?:project )?licen[sc]e|portions of this software are copyright .{1,40}? the freetype project", 40, 1.0),
    ("imagemagick", r"imagemagick licen[sc]e", 32, 0.95),
    ("json", r"the software shall be used for good, not evil", 45, 1.0),
    ("ms-pl", r"microsoft public licen[sc]e \(ms-pl\)", 42, 1.0),
    ("ms-rl", r"microsoft reciprocal licen[sc]e", 40, 1.0),
    ("nasa", r"nasa open source agreement", 40, 1.0),
    ("ncsa", r"university of illinois/ncsa open source licen[sc]e", 40, 1.0),
    ("ecl", r"educational community licen[sc]e", 32, 0.95),
    ("rpl", r"reciprocal public licen[sc]e", 32, 0.95),
    ("qpl", r"\bq public licen[sc]e", 32, 0.95),
    ("sleepycat", r"sleepycat licen[sc]e", 32, 0.95),
    ("sspl", r"server side public licen[sc]e", 40, 1.0),
    ("busl", r"business source licen[sc]e", 40, 1.0),
    ("elastic", r"elastic licen[sc]e", 32, 0.9),
    ("commons-clause", r"commons clause", 30, 0.8),
    ("polyform", r"polyform (?:noncommercial|small business|strict|shield|perimeter|internal use|free trial) licen[sc]e", 40, 1.0),
    ("openrail", r"\b(?:creativeml )?open ?rail(?:\+\+)?-?m(?![\w-])|responsible ai licen[sc]e", 38, 0.95),
    ("mulan", r"mulan (?:permissive software|psl|public) ?licen[sc]e", 40, 1.0),
    ("cecill", r"\bcecill(?:-[abc])?(?![\w])", 30, 0.9),
    ("etalab", r"licence ouverte(?: / open licen[sc]e)?", 30, 0.9),
    ("public-domain", r"(?:released|dedicated|placed|put) (?:in)?to the public domain", 25, 0.95),
    ("public-domain", r"\bin the public domain\b", 15, 0.8),
    ("public-domain", r"public domain dedication", 25, 0.95),
    ("public-domain", r"no copyright restrictions|this work is free of known copyright", 20, 0.85),
    ("proprietary", r"all rights reserved", 5, 0.6),
    ("proprietary", r"alle rechte vorbehalten|tous droits réservés|todos los derechos reservados|tutti i diritti riservati", 5, 0.6),
    ("proprietary", r"(?:proprietary and )?confidential(?: and proprietary)?[.,;: ]+(?:unauthori[sz]ed|do not)", 12, 0.8),
    ("proprietary", r"unauthori[sz]ed (?:copying|use|reproduction|distribution)(?: of this (?:file|software|document|material))?", 12, 0.8),
    ("proprietary", r"may not be (?:reproduced|copied|redistributed) without (?:the )?(?:prior |express )*(?:written )?(?:permission|consent)", 12, 0.8),
    ("proprietary", r"end[- ]user licen[sc]e agreement|\beula(?![\w-])", 20, 0.85),
    ("evaluation", r"for evaluation purposes only", 12, 0.7),
    ("non-commercial", r"for non-?commercial use only|not for commercial use|free for (?:personal|academic|non-?commercial) use", 14, 0.8),
    ("research-only", r"for research (?:purposes|use) only", 14, 0.8),
    ("no-ai", r"may not be used (?:to train|for training) (?:machine learning|artificial intelligence|ai|language) ?(?:models?|systems?)?", 30, 0.95),
    ("patent-grant", r"a perpetual, worldwide, non-exclusive, no-charge, royalty-free, irrevocable .{0,20}?patent licen[sc]e", 37, 0.9),
    ("contributor-agreement", r"contributor licen[sc]e agreement|developer certificate of origin", 20, 0.7),
    ("dual", r"dual[- ]licen[sc]ed", 20, 0.8),
    ("copyleft", r"share (?:alike|your work under the same licen[sc]e)|copyleft", 4, 0.4),
    ("open-source", r"open source (?:initiative|licen[sc]e)", 4, 0.4),
    ("license-file", r"see (?:the )?(?:accompanying )?(?:file )?(?:licen[sc]e|copying)(?:\.(?:txt|md))? (?:file )?(?:for|in the)", 6, 0.5),
    ("copyright-notice", r"(?:copyright|\(c\)|©) ?(?:\(c\)|©)? ?(?:19|20)\d\d(?:[-, ]+(?:19|20)\d\d)*", 3, 0.5),
    ("copyright-notice", r"copyright (?:holders?|owners?|notice)", 2, 0.3),
    ("no-warranty", r"without warrant(?:y|ies) of any kind", 2, 0.3),
    ("no-warranty", r"without any warranty|no warranty is (?:given|expressed)", 2, 0.3),
    ("no-liability", r"in no event shall .{1,60}? be (?:held )?liable", 2, 0.3),
]

#: Parts of keywords by which documents are told apart at first; keywords without one are gates themselves.
GATE_PARTS = ["licen", "copyright", "(c)", "©", "public", "permi", "warrant", "gpl", "redistribut", "bsd", "cc0", "ed under", "commons", "able under", "subject to ", "covered by ", "governed by ", "software", "rights reserved"]


#: Words that tell nothing.
COMMON = set("a an and any be by for from in is it may not of on or that the this to under v version with without you your".split())
#: Strings that an element of a pattern may have, a run of elements, and a set of keywords.
SPELLED, RUN, LISTED = 64, 8, 24


def rarity(text: str) -> int:
    """Length of what is uncommon in a string; marks that prose lacks count threefold."""
    words_ = re.findall(r"[^\W_]+", text)
    return sum(len(x) for x in words_ if x not in COMMON) + 3 * len(re.findall(r"[^\w\s.,;'\"-]", text))


def spellings(parsed) -> list[str] | None:
    """All strings that a parsed pattern can match, if they are few."""
    out = [""]
    for op, value in parsed:
        if op is kind.LITERAL:
            more = [chr(value)]
        elif op in (kind.AT, kind.ASSERT, kind.ASSERT_NOT):
            continue
        elif op is kind.IN and all(o is kind.LITERAL for o, _ in value):
            more = [chr(v) for _, v in value]
        elif op is kind.SUBPATTERN:
            more = spellings(value[3])
        elif op is kind.BRANCH:
            parts = [spellings(x) for x in value[1]]
            more = None if any(p is None for p in parts) else [y for p in parts for y in p]
        elif op in (kind.MAX_REPEAT, kind.MIN_REPEAT) and (value[0], value[1]) == (0, 1):
            one = spellings(value[2])
            more = None if one is None else ["", *one]
        else:
            more = None
        if more is None or len(out) * len(more) > SPELLED:
            return None
        out = [x + y for x in out for y in more]
    return out


def wanted(pattern: str) -> frozenset[str]:
    """Strings of which every match of the pattern holds at least one; empty if none is sure."""

    def least(options: list[str]) -> frozenset[str]:
        found = set(options)
        return frozenset(x for x in found if not any(y != x and y in x for y in found))

    def best(options: list[frozenset[str]]) -> frozenset[str]:
        options = [o for o in options if o and "" not in o and len(o) <= LISTED]
        return max(options, key=lambda o: (min(map(rarity, o)) - 0.1 * len(o), sorted(o)), default=frozenset())

    def of(parsed) -> frozenset[str]:
        options: list[frozenset[str]] = []
        run = [""]
        for item in parsed:
            op, value = item
            if op in (kind.AT, kind.ASSERT, kind.ASSERT_NOT):
                continue
            more = spellings([item])
            if more is not None and len(run) * len(more) <= RUN:
                run = [x + y for x in run for y in more]
                continue
            options.append(least(run))
            run = more or [""]
            if more is None:
                if op is kind.SUBPATTERN:
                    options.append(of(value[3]))
                elif op is kind.BRANCH:
                    branches = [of(x) for x in value[1]]
                    options.append(least([y for x in branches for y in x]) if all(branches) else frozenset())
                elif op in (kind.MAX_REPEAT, kind.MIN_REPEAT) and value[0]:
                    options.append(of(value[2]))
        return best([*options, least(run)])

    return of(parser.parse(pattern))


@cache
def rules() -> tuple[tuple[str, str, tuple[str, ...], int, float], ...]:
    """(label, pattern, keywords, priority, confidence) in order.

    A longer name has a higher priority by its length, so a specific license
    wins over the name that begins it.
    """
    out = [(label, rf"spdx-license-identifier: ?{re.escape(spdx)}(?:-only|-or-later|\+)?(?![\w.-])", 50, 1.0) for label, _, spdx in NAMES]
    for label, name, _ in NAMES:
        bare = name
        for grant, priority, sure in GRANTS:
            if label == "mit" and priority == 10:
                bare = r"(?:the )?mit licen[sc]e"
            out.append((label, grant.format(n=f"(?:{bare})") + r"(?![\w-])", priority, sure))
    out += SIGNATURES
    return tuple((a, b, tuple(sorted(wanted(b))), p, s) for a, b, p, s in out)


@cache
def gates() -> tuple[str, ...]:
    """A document without any of these has no detection: each keyword holds one."""
    found = {k: next((g for g in GATE_PARTS if g in k), k) for _, _, keys, _, _ in rules() for k in keys}
    return tuple(sorted(set(found.values())))


#: What parts words: all of ASCII but digits and letters.
_PARTS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words_of(lower: Column) -> Column:
    """Words of a text in lower case.

    Lower-casing letters beyond A-Z too changes no count and no place of a base
    phrase: no such letter becomes one of the letters of the phrases.
    """
    return F.array_remove(F.split(lower, _PARTS), "")


def _starts(words: Column) -> Column:
    """(word index, label) of every base phrase."""

    def at(i: Column) -> Column:
        found = F.lit(None).cast("string")
        for phrase, label in BASE.items():
            hit = F.lit(True)
            for k, word in enumerate(phrase.split()):
                hit = hit & (F.get(words, i + k) == word)
            found = F.when(hit, F.lit(label)).otherwise(found)
        return F.struct(i.cast("long").alias("at"), found.alias("label"))

    every = F.transform(F.sequence(F.lit(0), F.size(words) - 1), at)
    return F.filter(every, lambda x: x["label"].isNotNull())


def _detections(text: Column, rule: Column) -> Column:
    """Intervals of one rule in the text: what lies between matches gives offsets."""
    found = F.regexp_extract_all(text, rule["pattern"], F.lit(0))
    between = F.split(text, rule["pattern"], -1)
    ends = F.aggregate(
        F.zip_with(found, F.slice(between, 1, F.size(found)), lambda m, b: F.struct(F.length(b).alias("b"), F.length(m).alias("m"))),
        F.struct(F.lit(0).alias("pos"), F.array().cast("array<struct<start:int,end:int>>").alias("out")),
        lambda acc, x: F.struct(
            (acc["pos"] + x["b"] + x["m"]).alias("pos"),
            F.concat(acc["out"], F.array(F.struct((acc["pos"] + x["b"]).alias("start"), (acc["pos"] + x["b"] + x["m"]).alias("end")))).alias("out"),
        ),
        lambda acc: acc["out"],
    )
    return F.transform(
        F.when(F.size(found) > 0, ends).otherwise(F.array().cast("array<struct<start:int,end:int>>")),
        lambda x: F.struct(
            x["start"].alias("start"),
            x["end"].alias("end"),
            rule["priority"].alias("priority"),
            rule["id"].alias("id"),
            rule["label"].alias("label"),
            rule["sure"].alias("sure"),
        ),
    )


def _standing(detections: Column, levels: list[int]) -> Column:
    """Detections that no other one suppresses.

    In order of start, then of falling end, priority and rule, whatever holds an
    interval comes before it; so the largest end so far of each priority and those
    above it decides.
    """
    keyed = F.transform(detections, lambda d: F.struct(d["start"], -d["end"], -d["priority"], d["id"], d.alias("d")))
    rank = F.array(*[F.lit(p) for p in levels])
    none = F.array().cast("array<struct<start:int,end:int,priority:int,id:int,label:string,sure:double>>")

    def step(acc: Column, x: Column) -> Column:
        d = x["d"]
        at = F.array_position(rank, d["priority"]).cast("int")
        return F.struct(
            F.transform(acc["ends"], lambda e, i: F.when(i >= at - 1, F.greatest(e, d["end"])).otherwise(e)).alias("ends"),
            F.when(F.element_at(acc["ends"], at) >= d["end"], acc["out"]).otherwise(F.concat(acc["out"], F.array(d))).alias("out"),
        )

    start = F.struct(F.array(*[F.lit(-1) for _ in levels]).alias("ends"), none.alias("out"))
    return F.aggregate(F.array_sort(keyed), start, step, lambda acc: acc["out"])


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, detections.

    Places of detections are in the lower-cased text with white space folded.
    """
    listed = rules()
    words_ = sorted({k for _, _, keys, _, _ in listed for k in keys})
    at = {k: i for i, k in enumerate(words_)}
    shape = "array<struct<label:string,pattern:string,keys:array<int>,priority:int,id:int,sure:double>>"
    # A rule whose pattern gives no keyword is always tried.
    spelled = [{"label": a, "pattern": b, "keys": [at[x] for x in k], "priority": p, "id": i, "sure": s} for i, (a, b, k, p, s) in enumerate(listed)]
    table = F.from_json(F.lit(json.dumps(spelled)), shape)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_column().alias("text_"))
    rows = rows.withColumn("lower_", F.lower("text_")).withColumn("words_", words_of(F.col("lower_")))
    # Cheap: a base phrase needs its last word; the places are looked for only then.
    maybe = F.array_contains("words_", "license")
    no_place = F.array().cast("array<struct<at:bigint,label:string>>")
    rows = rows.select(
        "doc_id",
        F.regexp_replace("lower_", r"\s{2,}|[\t\n\x0B\f\r]", " ").alias("folded_"),
        F.size("words_").cast("long").alias("n_words"),
        F.when(maybe, _starts(F.col("words_"))).otherwise(no_place).alias("places_"),
    )
    text = F.col("folded_")
    gate = F.lit(any(not k for _, _, k, _, _ in listed))
    for word in gates():
        gate = gate | F.contains(text, F.lit(word))
    # One test a keyword, however many rules share it.
    rows = rows.withColumn("held_", F.when(gate, F.transform(F.array(*[F.lit(k) for k in words_]), lambda k: F.contains(text, k))))
    live = F.filter(table, lambda r: (F.size(r["keys"]) == 0) | F.exists(r["keys"], lambda k: F.get(F.col("held_"), k)))
    none = F.array().cast("array<struct<start:int,end:int,priority:int,id:int,label:string,sure:double>>")
    found = F.when(F.col("held_").isNotNull(), F.flatten(F.transform(live, lambda r: _detections(text, r)))).otherwise(none)
    levels = sorted({p for _, _, _, p, _ in listed}, reverse=True)
    rows = rows.withColumn("found_", found).withColumn("detections", F.when(F.size("found_") > 1, _standing(F.col("found_"), levels)).otherwise(F.col("found_")))
    base = F.array_sort(F.array_distinct(F.transform("places_", lambda p: p["label"])))
    own = F.transform("detections", lambda d: d["label"])
    sure = F.coalesce(F.array_max(F.transform("detections", lambda d: d["sure"])), F.lit(0.0))
    return rows.select(
        "doc_id",
        "n_words",
        F.size("places_").cast("long").alias("n_base"),
        F.array_min(F.transform("places_", lambda p: p["at"])).alias("first_word"),
        F.array_max(F.transform("places_", lambda p: p["at"])).alias("last_word"),
        F.array_join(base, ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_distinct(F.concat(base, own))), ",").alias("labels"),
        F.when(F.size("places_") > 0, F.greatest(sure, F.lit(0.9))).otherwise(sure).alias("score"),
        "detections",
    )
