"""License scans by ordered signature rules, in DataFrame functions only.

A text becomes its words (A-Z in lower case) with one blank between.  Rules are regular
expressions over those words, hand-written, each with a label, a priority and a confidence.  The
strings that every match of a rule holds are read off its pattern.  A cheap test for the few stems
that they share comes first; then a document meets only the rules whose strings it has.  Every match becomes an
interval of words; an interval inside another one of higher priority (or of equal priority and
greater length, or equal in both and earlier in the list) is suppressed, so that "apache license
version 2" is not reported as the family "apache" again.  Base phrases are counted at all their
places and are never suppressed.

Matches are marked in the text, whose marked words then tell their places; intervals are sorted, and
one meets only those before it that start within the longest match's reach.  Both take time in
proportion to the text.

Defined results: a null or empty text has no words, no labels and score 0; repeated rows give
repeated rows; extra columns are ignored.
"""

from __future__ import annotations

import json
from dataclasses import dataclass
from re import _parser as parser

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The base phrases and their labels, strings taken from a pattern at a time, and the characters between words.
BASE = (("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc"))
MOST_SPELLINGS, MOST_SETS = 10, 4
GAP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Pieces that most rules' words hold; ``gate`` adds the words of the other rules.
STEMS = ("licen", "copyright", "copyleft", "spdx", "public domain", "all rights reserved", "cc by", "cc0", "gpl", "creative commons", "redistribution", "free of charge", "warrant", "unlicense", "wtfpl", "patent", "cc zero")


@dataclass(frozen=True)
class Rule:
    label: str
    pattern: str
    priority: int
    confidence: float


#: label of a license, and its name in words (as a pattern)
NAMES = (
    ("mit", r"mit"), ("mit-0", r"mit (?:no attribution|0)"), ("x11", r"x11"), ("isc", r"isc"), ("0bsd", r"(?:0bsd|bsd zero clause)"),
    ("bsd-1", r"(?:bsd 1 clause|1 clause bsd|one clause bsd)"), ("bsd-2", r"(?:bsd 2 clause|2 clause bsd|two clause bsd|simplified bsd|freebsd)"), ("bsd-3", r"(?:bsd 3 clause|3 clause bsd|three clause bsd|new bsd|modified bsd|revised bsd)"), ("bsd-4", r"(?:bsd 4 clause|4 clause bsd|four clause bsd|original bsd)"), ("bsd", r"bsd(?: style)?"),
    ("apache-1", r"apache(?: software)?(?: license)?(?: version)? 1 0"), ("apache-1.1", r"apache(?: software)?(?: license)?(?: version)? 1 1"), ("apache-2", r"apache(?: software)?(?: license)?(?: version| v)? ?2(?: 0)?"), ("apache", r"apache(?: software)?"),
    ("gpl-1", r"(?:gnu )?(?:gpl|general public license)(?: version| v)? ?1(?: 0)?"), ("gpl-2", r"(?:gnu )?(?:gpl|general public license)(?: version| v)? ?2(?: 0)?"), ("gpl-3", r"(?:gnu )?(?:gpl|general public license)(?: version| v)? ?3(?: 0)?"), ("gpl", r"(?:gnu )?(?:gpl|general public)"),
    ("lgpl-2", r"(?:gnu )?(?:lgpl|library general public license)(?: version| v)? ?2(?: 0)?"), ("lgpl-2.1", r"(?:gnu )?(?:lgpl|lesser general public license)(?: version| v)? ?2 1"), ("lgpl-3", r"(?:gnu )?(?:lgpl|lesser general public license)(?: version| v)? ?3(?: 0)?"), ("lgpl", r"(?:gnu )?(?:lgpl|lesser general public|library general public)"),
    ("agpl-3", r"(?:gnu )?(?:agpl|affero general public license)(?: version| v)? ?3(?: 0)?"), ("agpl", r"(?:gnu )?(?:agpl|affero general public)"), ("gfdl", r"(?:gnu )?(?:gfdl|free documentation)"),
    ("mpl-1.1", r"(?:mpl|mozilla public license)(?: version| v)? ?1 1"), ("mpl-2", r"(?:mpl|mozilla public license)(?: version| v)? ?2(?: 0)?"), ("mpl", r"(?:mpl|mozilla public)"),
    ("epl-1", r"(?:epl|eclipse public license)(?: version| v)? ?1(?: 0)?"), ("epl-2", r"(?:epl|eclipse public license)(?: version| v)? ?2(?: 0)?"), ("epl", r"(?:epl|eclipse public)"),
    ("cddl", r"(?:cddl|common development and distribution)"), ("cpl", r"common public"), ("eupl", r"(?:eupl|european union public)"), ("artistic-2", r"artistic license 2(?: 0)?"), ("artistic", r"artistic"), ("perl", r"perl"), ("php", r"php"), ("python", r"(?:python software foundation|psf|python)"),
    ("zlib", r"zlib(?: libpng)?"), ("libpng", r"libpng"), ("boost", r"boost(?: software)?"), ("bsl-1.1", r"business source"), ("elastic-2", r"elastic(?: license)?(?: version)? 2(?: 0)?"), ("elastic", r"elastic"), ("sspl", r"server side public"), ("unlicense", r"unlicense"), ("wtfpl", r"(?:wtfpl|do what the fuck you want to public)"),
    ("openssl", r"openssl"), ("ofl", r"(?:sil )?open font"), ("ms-pl", r"microsoft public"), ("ms-rl", r"microsoft reciprocal"), ("ncsa", r"(?:university of illinois )?ncsa(?: open source)?"), ("postgresql", r"postgresql"), ("vim", r"vim"), ("ruby", r"ruby"), ("osl-3", r"open software license(?: version)? 3 0"), ("afl-3", r"academic free(?: license)?(?: version)? 3 0"), ("odbl", r"(?:open database|odbl)"), ("odc-by", r"open data commons attribution"), ("pddl", r"public domain dedication"), ("cecill", r"cecill"), ("upl", r"universal permissive"), ("openrail", r"(?:open ?rail(?: m)?|responsible ai)"), ("community-model", r"community"),
)
#: what stands around a name: (pattern with %s for the name, priority, confidence)
SETTINGS = (
    (r"(?:released|licensed|distributed|available|published|covered|provided|redistributed|made available) under (?:the )?(?:terms of )?(?:the )?(?:a )?%s(?: license| licence)?", 60, 0.95),
    (r"under (?:the )?(?:terms|conditions|provisions) (?:and conditions )?of (?:the )?%s(?: license| licence)?", 50, 0.9),
    (r"spdx license identifier %s", 80, 1.0),
    (r"(?:the )?%s (?:license|licence)", 40, 0.8),
    (r"licen[sc]e(?:d)?(?: is| as| type)? %s", 35, 0.7),
)
#: hand-written passages and notices
NOTICES = (
    Rule("mit", r"permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", 90, 1.0),
    Rule("mit", r"permission is hereby granted free of charge", 30, 0.7),
    Rule("isc", r"permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", 90, 1.0),
    Rule("bsd", r"redistribution and use in source and binary forms with or without modification are permitted", 70, 0.95),
    Rule("bsd-3", r"neither the name of .{1,80} nor the names of its contributors may be used to endorse", 75, 0.95),
    Rule("apache-2", r"you may not use this file except in compliance with the license", 70, 0.9),
    Rule("apache-2", r"apache org licenses license 2 0", 85, 1.0),
    Rule("gpl", r"this program is free software you can redistribute it and or modify it", 65, 0.9),
    Rule("gpl-2-or-later", r"either version 2 of the license or (?:at your option )?any later version", 75, 0.9),
    Rule("gpl-3-or-later", r"either version 3 of the license or (?:at your option )?any later version", 75, 0.9),
    Rule("gpl-3", r"gnu general public license version 3", 70, 1.0),
    Rule("gpl-2", r"gnu general public license version 2", 70, 1.0),
    Rule("gpl", r"gnu org licenses(?: gpl)?(?: html| txt)?", 45, 0.8),
    Rule("cc0", r"cc0(?: 1 0)?(?: universal)?", 70, 0.95),
    Rule("cc0", r"creative commons (?:zero|0|public domain dedication)(?: 1 0)?(?: universal)?", 70, 0.95),
    Rule("cc-by-nc-nd", r"cc by nc nd(?: [1-4] [05])?", 78, 1.0),
    Rule("cc-by-nc-sa", r"cc by nc sa(?: [1-4] [05])?", 78, 1.0),
    Rule("cc-by-nc", r"cc by nc(?: [1-4] [05])?", 74, 1.0),
    Rule("cc-by-nd", r"cc by nd(?: [1-4] [05])?", 74, 1.0),
    Rule("cc-by-sa", r"cc by sa(?: [1-4] [05])?", 74, 1.0),
    Rule("cc-by", r"cc by(?: [1-4] [05])?", 70, 0.9),
    Rule("cc-by-nc-sa", r"creative commons attribution non ?commercial share ?alike(?: [1-4] [05])?", 78, 1.0),
    Rule("cc-by-nc-nd", r"creative commons attribution non ?commercial no ?deriv(?:ative)?s?(?: works)?(?: [1-4] [05])?", 78, 1.0),
    Rule("cc-by-nc", r"creative commons attribution non ?commercial(?: [1-4] [05])?", 74, 1.0),
    Rule("cc-by-sa", r"creative commons attribution share ?alike(?: [1-4] [05])?", 74, 1.0),
    Rule("cc-by-nd", r"creative commons attribution no ?deriv(?:ative)?s?(?: works)?(?: [1-4] [05])?", 74, 1.0),
    Rule("cc-by", r"creative commons attribution(?: [1-4] [05])?", 70, 0.95),
    Rule("creative-commons", r"creative commons", 20, 0.5),
    Rule("public-domain", r"(?:released|dedicated|placed|put) (?:in|in to|into|to) the public domain", 70, 0.95),
    Rule("public-domain", r"(?:this work is|is) in the public domain", 60, 0.8),
    Rule("public-domain", r"public domain", 15, 0.4),
    Rule("unlicense", r"this is free and unencumbered software released into the public domain", 90, 1.0),
    Rule("all-rights-reserved", r"all rights reserved", 25, 0.6),
    Rule("copyright", r"copyright(?: c)? (?:19|20)[0-9]{2}(?: (?:19|20)[0-9]{2})*", 25, 0.5),
    Rule("copyright", r"copyright", 5, 0.2),
    Rule("copyleft", r"copyleft", 10, 0.4),
    Rule("patent-grant", r"(?:royalty free|irrevocable) patent license", 40, 0.6),
    Rule("no-warranty", r"without warranty of any kind express or implied", 30, 0.5),
    Rule("no-warranty", r"without any warranty without even the implied warranty of merchantability", 30, 0.5),
    Rule("non-commercial", r"(?:for )?non ?commercial (?:use|purposes)(?: only)?", 30, 0.6),
    Rule("research-only", r"(?:for )?research (?:use|purposes) only", 30, 0.6),
    Rule("proprietary", r"proprietary (?:license|licence|software)", 35, 0.7),
    Rule("dual-license", r"(?:dual|dually|multi|triple) licen[sc]ed", 35, 0.6),
    Rule("end-user-license", r"end user licen[sc]e agreement", 40, 0.8),
    Rule("license-reference", r"see (?:the )?(?:accompanying )?licen[sc]e(?: file)?(?: for (?:more )?(?:details|information))?", 12, 0.3),
    Rule("license-mention", r"licen[sc]ed under", 4, 0.2),
)

#: more hand-written rules: label | priority | confidence | pattern
WRITTEN = r"""
mit | 88 | 1.0 | the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software
mit | 72 | 0.9 | without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software
mit | 60 | 0.8 | in no event shall the authors or copyright holders be liable for any claim damages or other liability
mit | 45 | 0.8 | opensource org licenses mit(?: license)?(?: php| html)?
mit | 44 | 0.7 | (?:see|read) (?:the )?mit licen[sc]e
mit-0 | 74 | 0.95 | mit no attribution licen[sc]e
mit-modern | 70 | 0.9 | modern variant of the mit licen[sc]e
x11 | 70 | 0.9 | x consortium shall not be used in advertising or otherwise .{0,80}copyright
isc | 45 | 0.8 | opensource org licenses isc(?: license)?
isc | 72 | 0.9 | the software is provided as is and the author disclaims all warranties with regard to this software
0bsd | 74 | 0.95 | permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted free of charge
bsd-2 | 78 | 0.95 | redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer
bsd-2 | 79 | 0.95 | redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer
bsd-2 | 45 | 0.8 | opensource org licenses bsd 2 clause
bsd-3 | 45 | 0.8 | opensource org licenses bsd (?:3 clause|license)(?: php)?
bsd-4 | 78 | 1.0 | all advertising materials mentioning features or use of this software must display the following acknowledge?ment.{0,60}copyright
bsd-patent | 74 | 0.95 | bsd(?: 2 clause)? plus patent licen[sc]e
bsd | 46 | 0.8 | (?:use of this source code is )?governed by a bsd style licen[sc]e
bsd | 40 | 0.7 | berkeley software distribution licen[sc]e
apache-2 | 82 | 1.0 | licensed under the apache license version 2 0 the license
apache-2 | 66 | 0.9 | unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis
apache-2 | 58 | 0.8 | see the license for the specific language governing permissions and limitations under the license
apache-2 | 60 | 0.9 | perpetual worldwide non exclusive no charge royalty free irrevocable (?:copyright|patent) license
apache-2 | 50 | 0.8 | asl ?2(?: 0)? licen[sc]e
apache-1.1 | 70 | 0.9 | this product includes software developed by the apache software foundation .{0,40}licen[sc]e
gpl | 62 | 0.9 | under the terms of the gnu general public license as published by the free software foundation
gpl | 58 | 0.8 | you should have received a copy of the gnu general public license
gpl | 40 | 0.6 | gnu general public licen[sc]e
gpl-2-only | 78 | 1.0 | gpl 2(?: 0)? only
gpl-2-or-later | 78 | 1.0 | gpl 2(?: 0)? or later
gpl-3-only | 78 | 1.0 | gpl 3(?: 0)? only
gpl-3-or-later | 78 | 1.0 | gpl 3(?: 0)? or later
gpl-2 | 68 | 0.95 | gplv2
gpl-2-or-later | 72 | 0.95 | gplv2 ?(?:or later|and later)
gpl-3 | 68 | 0.95 | gplv3
gpl-3-or-later | 72 | 0.95 | gplv3 ?(?:or later|and later)
gpl-2-classpath | 82 | 1.0 | gpl ?v?2(?: 0)? with (?:the )?classpath exception
gpl-classpath | 66 | 0.9 | as a special exception the copyright holders of this library give you permission to link this library with independent modules
gpl-autoconf | 66 | 0.9 | gpl .{0,40}autoconf exception
gpl-bison | 66 | 0.9 | gpl .{0,40}bison exception
gpl-gcc | 66 | 0.9 | gcc runtime library exception .{0,40}gpl
gpl-gcc | 66 | 0.9 | gpl .{0,40}gcc runtime library exception
gpl-font | 66 | 0.9 | gpl .{0,40}font exception
gpl-openssl | 66 | 0.9 | gpl .{0,40}openssl exception
lgpl | 60 | 0.8 | you should have received a copy of the gnu (?:lesser|library) general public license
lgpl | 64 | 0.9 | under the terms of the gnu (?:lesser|library) general public license as published by the free software foundation
lgpl-2.1-only | 78 | 1.0 | lgpl 2 1 only
lgpl-2.1-or-later | 78 | 1.0 | lgpl 2 1 or later
lgpl-3-only | 78 | 1.0 | lgpl 3(?: 0)? only
lgpl-3-or-later | 78 | 1.0 | lgpl 3(?: 0)? or later
lgpl-2.1 | 68 | 0.95 | lgplv2 1
lgpl-3 | 68 | 0.95 | lgplv3
agpl-3 | 68 | 0.95 | agplv3
agpl-3-only | 78 | 1.0 | agpl 3(?: 0)? only
agpl-3-or-later | 78 | 1.0 | agpl 3(?: 0)? or later
agpl | 64 | 0.9 | under the terms of the gnu affero general public license as published by the free software foundation
gfdl | 64 | 0.9 | permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation license
gfdl-1.2 | 74 | 0.95 | gnu free documentation license version 1 2
gfdl-1.3 | 74 | 0.95 | gnu free documentation license version 1 3
gfdl-no-invariants | 70 | 0.9 | with no invariant sections no front cover texts and no back cover texts .{0,60}license
mpl-1.1 | 76 | 0.95 | the contents of this file are subject to the mozilla public license version 1 1
mpl-2 | 78 | 1.0 | this source code form is subject to the terms of the mozilla public license v 2 0
mpl-2 | 56 | 0.9 | mozilla org mpl 2 0
mpl-2-no-copyleft | 70 | 0.9 | this source code form is incompatible with secondary licenses
npl | 70 | 0.9 | netscape public licen[sc]e
epl-1 | 76 | 0.95 | this program and the accompanying materials are made available under the terms of the eclipse public license v1 0
epl-2 | 76 | 0.95 | this program and the accompanying materials are made available under the terms of the eclipse public license 2 0
epl | 46 | 0.8 | eclipse org legal epl .{0,20}licen[sc]e
edl | 70 | 0.9 | eclipse distribution licen[sc]e(?: v ?1 0)?
cddl-1 | 74 | 0.95 | common development and distribution license(?: cddl)? version 1 0
cddl-1.1 | 74 | 0.95 | common development and distribution license(?: cddl)? version 1 1
ibm-pl | 70 | 0.9 | ibm public licen[sc]e(?: version 1 0)?
eupl-1.1 | 74 | 0.95 | european union public licen[sc]e(?: v| version)? ?1 1
eupl-1.2 | 74 | 0.95 | european union public licen[sc]e(?: v| version)? ?1 2
artistic-1 | 72 | 0.9 | artistic license(?: version)? 1 0
artistic-perl | 74 | 0.95 | (?:same|under the same) terms as perl itself .{0,60}licen[sc]e
zlib | 78 | 0.95 | the origin of this software must not be misrepresented you must not claim that you wrote the original software
zlib | 72 | 0.9 | permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely
boost | 80 | 1.0 | distributed under the boost software license version 1 0
boost | 46 | 0.8 | boost org license 1 0
python | 72 | 0.9 | python software foundation licen[sc]e(?: version)? 2
cnri-python | 72 | 0.9 | cnri (?:open source )?licen[sc]e
php-3 | 74 | 0.95 | php license version 3 0(?:1)?
ruby | 64 | 0.8 | ruby s licen[sc]e
curl | 70 | 0.9 | curl licen[sc]e
curl | 70 | 0.9 | licensed as described in the file copying .{0,60}copyright
openssl | 74 | 0.95 | this product includes software developed by the openssl project .{0,80}licen[sc]e
sleepycat | 70 | 0.9 | sleepycat (?:public )?licen[sc]e
w3c | 70 | 0.9 | w3c software (?:and document )?(?:notice and )?licen[sc]e
ntp | 72 | 0.9 | permission to use copy modify and distribute this software and its documentation for any purpose .{0,60}copyright notice
hpnd | 70 | 0.9 | historical permission notice and disclaimer .{0,40}licen[sc]e
ncsa | 72 | 0.9 | university of illinois ncsa open source licen[sc]e
unicode | 72 | 0.9 | unicode (?:inc )?licen[sc]e agreement
unicode | 66 | 0.8 | unicode terms of use .{0,40}licen[sc]e
icu | 68 | 0.9 | icu licen[sc]e
tcl | 64 | 0.8 | tcl tk licen[sc]e
naist | 66 | 0.9 | naist licen[sc]e
qpl | 70 | 0.9 | q public licen[sc]e(?: version 1 0)?
apsl | 70 | 0.9 | apple public source licen[sc]e(?: version)?(?: 2 0)?
nasa | 70 | 0.9 | nasa open source agreement .{0,40}licen[sc]e
rpl | 70 | 0.9 | reciprocal public licen[sc]e
osl | 66 | 0.85 | open software licen[sc]e
afl | 66 | 0.85 | academic free licen[sc]e
ecl-2 | 72 | 0.9 | educational community licen[sc]e(?: version)? 2 0
simpl | 68 | 0.9 | simple public licen[sc]e
mulan-psl-2 | 74 | 0.95 | mulan (?:psl|permissive software licen[sc]e)(?: v| version)? ?2
mulan-psl | 66 | 0.9 | mulan permissive software licen[sc]e
cecill-b | 74 | 0.95 | cecill b licen[sc]e
cecill-c | 74 | 0.95 | cecill c licen[sc]e
cecill-2 | 74 | 0.95 | cecill(?: licen[sc]e)? (?:version )?2 [01] licen[sc]e
beerware | 74 | 0.9 | beer ?ware licen[sc]e
beerware | 76 | 0.95 | as long as you retain this notice you can do whatever you want with this stuff .{0,80}licen[sc]e
json | 76 | 0.95 | the software shall be used for good not evil
wtfpl | 80 | 1.0 | do what the fuck you want to public license
unlicense | 72 | 0.9 | anyone is free to copy modify publish use compile sell or distribute this software
unlicense | 50 | 0.9 | unlicense org
cc0 | 66 | 0.9 | creativecommons org publicdomain zero 1 0 .{0,40}licen[sc]e
cc0 | 74 | 0.95 | the person who associated a work with this deed has dedicated the work to the public domain
cc-pdm | 70 | 0.9 | public domain mark(?: 1 0)?
cc-by-1 | 78 | 1.0 | creative commons attribution 1 0 generic
cc-by-2 | 78 | 1.0 | creative commons attribution 2 0 (?:generic|unported)
cc-by-2.5 | 78 | 1.0 | creative commons attribution 2 5 (?:generic|unported)
cc-by-3 | 78 | 1.0 | creative commons attribution 3 0 unported
cc-by-4 | 78 | 1.0 | creative commons attribution 4 0 international
cc-by-sa-3 | 80 | 1.0 | creative commons attribution share ?alike 3 0 unported
cc-by-sa-4 | 80 | 1.0 | creative commons attribution share ?alike 4 0 international
cc-by-nc-4 | 80 | 1.0 | creative commons attribution non ?commercial 4 0 international
cc-by-nd-4 | 80 | 1.0 | creative commons attribution no ?derivatives 4 0 international
cc-by-nc-sa-4 | 82 | 1.0 | creative commons attribution non ?commercial share ?alike 4 0 international
cc-by-nc-nd-4 | 82 | 1.0 | creative commons attribution non ?commercial no ?derivatives 4 0 international
cc-sampling | 74 | 0.9 | creative commons sampling plus
cc-devnations | 74 | 0.9 | creative commons developing nations
creative-commons | 36 | 0.6 | (?:under|with) (?:a|the) creative commons licen[sc]e
creative-commons | 30 | 0.5 | some rights reserved
ofl-1.1 | 78 | 1.0 | sil open font license version 1 1
ofl | 56 | 0.85 | scripts sil org ofl .{0,40}licen[sc]e
ofl-rfn | 70 | 0.9 | with reserved font name .{0,60}licen[sc]e
ubuntu-font | 70 | 0.9 | ubuntu font licen[sc]e(?: version 1 0)?
bitstream-vera | 70 | 0.9 | bitstream vera .{0,60}copyright
lppl | 72 | 0.9 | latex project public licen[sc]e(?: version 1 [23])?
lppl | 74 | 0.95 | this work may be distributed and or modified under the conditions of the latex project public license
fsf-free | 60 | 0.8 | this file is free software .{0,80}unlimited permission to copy and or distribute it
fsf-all-permissive | 74 | 0.95 | copying and distribution of this file with or without modification are permitted in any medium without royalty
odbl | 74 | 0.95 | open database license(?: odbl)?(?: v| version)? ?1 0
odc-by | 74 | 0.95 | open data commons attribution license
pddl | 74 | 0.95 | open data commons public domain dedication and licen[sc]e
dbcl | 72 | 0.9 | database contents licen[sc]e
cdla-permissive | 74 | 0.95 | community data license agreement permissive
cdla-sharing | 74 | 0.95 | community data license agreement sharing
ogl-uk | 74 | 0.95 | open government licen[sc]e(?: v| version)? ?(?:1|2|3) 0
ogl | 62 | 0.85 | open government licen[sc]e
etalab | 72 | 0.9 | (?:licence ouverte|etalab) open licen[sc]e
dl-de-by | 74 | 0.95 | data licence germany attribution version 2 0
dl-de-zero | 74 | 0.95 | data licence germany zero version 2 0
gutenberg | 76 | 0.95 | project gutenberg (?:tm )?licen[sc]e
gutenberg | 64 | 0.8 | this ebook is for the use of anyone anywhere .{0,120}licen[sc]e
us-government | 70 | 0.9 | work of the united states government .{0,80}public domain
us-government | 66 | 0.85 | not subject to copyright protection in the united states
crown-copyright | 66 | 0.85 | crown copyright
public-domain | 64 | 0.85 | (?:released|given|dedicated) to the public domain
public-domain | 62 | 0.85 | no (?:known )?copyright restrictions
public-domain | 62 | 0.85 | copyright (?:has )?expired
public-domain | 60 | 0.8 | free of (?:known )?copyright restrictions
orphan-work | 40 | 0.5 | copyright status (?:is )?(?:unknown|undetermined)
fair-use | 40 | 0.6 | fair use .{0,80}copyright(?:ed)?
bsl-1.1 | 78 | 0.95 | business source license 1 1
bsl-1.1 | 70 | 0.9 | additional use grant .{0,80}licen[sc]e
sspl-1 | 78 | 0.95 | server side public license(?: v| version)? ?1
elastic-2 | 76 | 0.95 | elastic license 2 0 .{0,40}licensor
confluent | 72 | 0.9 | confluent community licen[sc]e
timescale | 72 | 0.9 | timescale licen[sc]e
redis-rsal | 72 | 0.9 | redis source available licen[sc]e
commons-clause | 74 | 0.95 | commons clause (?:licen[sc]e )?condition
commons-clause | 66 | 0.9 | the grant of rights under the license will not include .{0,60}right to sell the software
polyform-nc | 74 | 0.95 | polyform non ?commercial licen[sc]e
polyform-sb | 74 | 0.95 | polyform small business licen[sc]e
polyform-strict | 74 | 0.95 | polyform strict licen[sc]e
polyform-shield | 74 | 0.95 | polyform shield licen[sc]e
parity | 70 | 0.9 | parity public licen[sc]e
prosperity | 70 | 0.9 | prosperity public licen[sc]e
blue-oak | 74 | 0.95 | blue oak model licen[sc]e
hippocratic | 72 | 0.9 | hippocratic licen[sc]e
anti-996 | 72 | 0.9 | anti 996 licen[sc]e
fair-source | 70 | 0.9 | fair source licen[sc]e
functional-source | 72 | 0.9 | functional source licen[sc]e
bigscience-rail | 74 | 0.95 | bigscience (?:open )?rail(?: m)? licen[sc]e
creativeml-rail | 74 | 0.95 | creativeml open ?rail(?: m)? licen[sc]e
openrail-plus | 72 | 0.9 | openrail plus plus .{0,20}licen[sc]e
llama-community | 74 | 0.95 | llama ?[0-9]? ?[0-9]? community licen[sc]e
gemma-terms | 68 | 0.9 | gemma terms of use .{0,60}licen[sc]e
opt-175b | 70 | 0.9 | opt 175b licen[sc]e
research-only | 60 | 0.8 | for non ?commercial research purposes only .{0,60}licen[sc]e
evaluation-only | 50 | 0.7 | evaluation licen[sc]e
trial | 45 | 0.6 | trial (?:version )?licen[sc]e
shareware | 45 | 0.7 | shareware licen[sc]e
freeware | 45 | 0.7 | freeware licen[sc]e
donationware | 45 | 0.7 | donation ?ware licen[sc]e
postcardware | 45 | 0.7 | postcard ?ware licen[sc]e
commercial | 46 | 0.75 | commercial licen[sc]e(?: agreement)?
enterprise | 44 | 0.7 | enterprise licen[sc]e(?: agreement)?
site-license | 42 | 0.6 | site licen[sc]e(?: agreement)?
subscription | 42 | 0.6 | subscription licen[sc]e(?: agreement)?
end-user-license | 46 | 0.85 | by (?:installing|using|downloading) (?:this|the) software you agree to .{0,60}licen[sc]e
proprietary | 50 | 0.8 | (?:confidential and proprietary|proprietary and confidential) .{0,80}copyright
proprietary | 48 | 0.8 | unauthori[sz]ed (?:copying|use|reproduction|distribution) .{0,60}copyright
proprietary | 46 | 0.75 | no part of this (?:publication|document|work|book) may be reproduced .{0,80}copyright
proprietary | 40 | 0.7 | may not be (?:reproduced|copied|distributed) without (?:the )?(?:prior )?(?:written )?(?:permission|consent) of the copyright (?:holder|owner)s?
no-derivatives | 40 | 0.6 | no derivative works .{0,40}licen[sc]e
attribution-required | 36 | 0.5 | attribution (?:is )?required .{0,40}licen[sc]e
share-alike | 36 | 0.5 | share ?alike licen[sc]e
dual-license | 44 | 0.7 | licen[sc]ed under either of
dual-license | 46 | 0.8 | (?:apache .{0,20}or mit|mit or apache.{0,20}) at your option .{0,40}licen[sc]e
contributor-agreement | 44 | 0.7 | contributor licen[sc]e agreement
license-exception | 30 | 0.5 | licen[sc]e (?:linking )?exception
license-compatible | 24 | 0.4 | (?:gpl|licen[sc]e) compatible
sublicense | 22 | 0.4 | right to sublicen[sc]e
royalty-free | 24 | 0.5 | royalty free licen[sc]e
perpetual | 24 | 0.5 | perpetual licen[sc]e
no-warranty | 34 | 0.5 | provided as is without (?:any )?warranty(?: of any kind)?
no-warranty | 32 | 0.5 | (?:comes with )?absolutely no warranty
no-warranty | 30 | 0.5 | disclaims? all warranties
no-warranty | 28 | 0.4 | implied warrant(?:y|ies) of merchantability (?:and|or) fitness for a particular purpose
patent-grant | 34 | 0.5 | patent (?:grant|rights)
patent-pending | 20 | 0.4 | patents? pending
trademark | 20 | 0.3 | trademarks? .{0,40}copyright
copyright | 28 | 0.5 | copyright (?:holder|owner)s?
copyright | 26 | 0.5 | copyright notice
license-file | 14 | 0.3 | licen[sc]e (?:txt|md|rst)
license-terms | 14 | 0.3 | licen[sc]e terms
license-agreement | 16 | 0.4 | licen[sc]e agreement
license-header | 14 | 0.3 | licen[sc]e header
"""


def written() -> list[Rule]:
    """The rules of WRITTEN."""
    rows = (line.split(" | ") for line in WRITTEN.strip().splitlines())
    return [Rule(label, pattern, int(priority), float(confidence)) for label, priority, confidence, pattern in rows]



def rules() -> list[Rule]:
    """All rules, the base phrases first, then by falling priority (their order breaks ties)."""
    out = [*NOTICES, *written()]
    for label, name in NAMES:
        more = 5 if any(c.isdigit() for c in label) else 0
        out += [Rule(label, setting % name, priority + more, confidence) for setting, priority, confidence in SETTINGS]
    base = [Rule(label, text, 100, 1.0) for text, label in BASE]
    return base + sorted(out, key=lambda r: -r.priority)


def _least(words: set[str]) -> tuple[str, ...]:
    """Without those that hold another one."""
    return tuple(sorted(w for w in words if not any(o != w and o in w for o in words)))


def _spellings(nodes) -> set[str] | None:
    """All strings that the parsed pattern matches; None if they are more than MOST_SPELLINGS."""
    out = {""}
    for kind, arg in nodes:
        if kind is parser.LITERAL:
            some = {chr(arg)}
        elif kind is parser.IN and all(k is parser.LITERAL for k, _ in arg):
            some = {chr(c) for _, c in arg}
        elif kind is parser.SUBPATTERN:
            some = _spellings(arg[-1])
        elif kind is parser.BRANCH:
            parts = [_spellings(x) for x in arg[1]]
            some = None if None in parts else set().union(*parts)
        elif kind is parser.MAX_REPEAT and arg[:2] == (0, 1):
            some = _spellings(arg[2])
            some = some and some | {""}
        else:
            some = None
        if some is None or len(out) * len(some) > MOST_SPELLINGS:
            return None
        out = {a + b for a in out for b in some}
    return out


def needs(pattern: str) -> list[tuple[str, ...]]:
    """Sets of strings: every match of ``pattern`` holds at least one string of each set."""
    out, run = [], {""}
    for node in parser.parse(pattern):
        some = _spellings([node])
        if some is None or len(run) * len(some) > MOST_SPELLINGS:
            out.append(run)
            run = {""}
        run = {a + b for a in run for b in some or {""}}
    return [_least(w) for w in [*out, run] if "" not in w]


#: Words that many rules hold tell little.
STOCK = frozenset("licen license licence licensed the of under terms version public software general this for and copyright creative commons attribution open any free with to is permission distributed".split())


def key_words(pattern: str) -> list[tuple[str, ...]]:
    """The most telling MOST_SETS of ``needs``, by the longest word of each string that is no stock word."""
    telling = lambda w: (w not in STOCK, len(w), w)
    sets = {_least({max(w.split(), key=telling) for w in words}) for words in needs(pattern) if all(w.split() for w in words)}
    return sorted(sets, key=lambda w: (len(w), -min(map(len, w)), w))[:MOST_SETS]


def gate(listed: list[Rule]) -> list[str]:
    """Strings of which a text that any rule matches holds at least one."""
    out = set()
    for r in listed:
        sets = needs(r.pattern)
        stems = ({next((s for s in STEMS if s in w), None) for w in words} for words in sets)
        out |= next((s for s in stems if None not in s), None) or set(max(sets, key=lambda words: min(map(len, words))))
    return list(_least(out))


def constant(rows: list, kind: str) -> Column:
    """An array as one literal: the optimizer folds it, where hundreds of nested literals would be planned
    one by one."""
    if " " not in kind:
        return F.from_json(F.lit(json.dumps(rows)), f"array<{kind}>")
    names = [c.split()[0] for c in kind.split(", ")]
    fields = ", ".join(c.replace(" ", ":", 1) for c in kind.split(", "))
    return F.from_json(F.lit(json.dumps([dict(zip(names, r, strict=True)) for r in rows])), f"array<struct<{fields}>>")


def words_text(text: Column) -> Column:
    """Words with a blank before each and one at the end; A-Z in lower case, all else as it is."""
    plain = F.octet_length(text) == F.length(text)  # then no other letters are changed
    lower = F.when(plain, F.lower(text)).otherwise(F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    return F.concat(F.lit(" "), F.trim(F.regexp_replace(lower, GAP, " ")), F.lit(" "))


def may_hold(lower: Column, stems: list[str]) -> Column:
    """Whether a lower-cased raw text has one of the stems; any gap may stand between the words of one.  (Lower
    case may turn other letters into a-z, which lets more through only.)  The stems' longest words come first."""
    by_word: dict[str, list[str]] = {}
    for stem in stems:
        by_word.setdefault(max(stem.split(), key=len), []).append(GAP.join(stem.split()))
    flag = F.lit(False)
    for word, patterns in by_word.items():
        has = F.contains(lower, F.lit(word))
        flag = flag | (has if word in patterns else has & lower.rlike("|".join(patterns)))
    return F.exists(constant(list(_least(set(by_word))), "string"), lambda word: F.contains(lower, word)) & flag


def matches(norm: Column, pattern: Column) -> Column:
    """(s, e) in words of all matches that do not overlap; ``pattern`` stands between blanks.

    The first and the last word of a match are marked; the words' numbers are its place."""
    full = F.concat(F.lit("(?<= )("), pattern, F.lit(")(?= )"))
    words = F.split(F.trim(F.regexp_replace(norm, full, F.lit("\x01$1\x02"))), " ")
    places = lambda mark: F.array_compact(F.transform(words, lambda w, i: F.when(mark(w), i)))
    return F.zip_with(places(lambda w: F.startswith(w, F.lit("\x01"))), places(lambda w: F.endswith(w, F.lit("\x02"))), lambda s, e: F.struct(s.alias("s"), (e + 1).alias("e")))


#: Hits that are looked back over; a document takes the first number that reaches far enough.
BACK = (16, 128, 1024)


def resolved(df: DataFrame, is_base) -> DataFrame:
    """``df(hits)`` with ``kept``: without hits inside a better one.  Hits are sorted by start, falling end and
    falling rank, so that what covers a hit stands before it, and starts no further back than the longest
    hit is long.  How far to look back is a column of its own: inside the filter it would be taken anew
    for every hit."""
    hits, longest, back = F.col("hits"), F.col("longest"), F.col("back")
    rank = lambda h: F.struct(h["p"], h["len"], h["o"])
    enough = lambda n: F.forall(F.sequence(F.lit(0), F.size(hits) - 1), lambda k: (k < n) | (F.get(hits, k - n)["s"] + longest < F.get(hits, k)["s"]))
    reach = F.size(hits)
    for n in reversed(BACK):
        reach = F.when(F.size(hits) <= n, n).when(enough(n), n).otherwise(reach)

    def stays(h: Column, k: Column) -> Column:
        before = F.slice(hits, F.greatest(k - back, F.lit(0)) + 1, F.least(k, back))
        return is_base(h) | ~F.exists(before, lambda g: (h["e"] <= g["e"]) & (rank(g) > rank(h)))

    out = df.withColumn("longest", F.array_max(F.transform(hits, lambda h: h["len"]))).withColumn("back", F.when(F.size(hits) > 1, reach))
    return out.withColumn("kept", F.when(F.size(hits) <= 1, hits).otherwise(F.filter(hits, stays)))


def scan(docs: DataFrame, *, gated: bool = True) -> DataFrame:
    """Per row of ``docs``: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score.

    ``gated=False`` tries every rule on every text, with the same result."""
    listed = rules()
    stems = gate(listed)
    raw = F.coalesce(F.col("text"), F.lit(""))
    text, lower, parts = F.col("text"), F.col("lower"), F.col("parts")
    # steps of their own: what later steps use more than once is taken once
    one = docs.select("doc_id", raw.alias("text"), F.lower(raw).alias("lower")).withColumn("parts", F.split(lower, GAP))
    last = F.get(parts, F.size(parts) - 1)
    n_words = F.size(parts) - (F.get(parts, F.lit(0)) == "").cast("int") - ((F.size(parts) > 1) & (last == "")).cast("int")
    flag = may_hold(lower, stems) if gated else F.lit(True)
    one = one.select("doc_id", n_words.cast("long").alias("n_words"), F.when(flag, words_text(text)).alias("norm"))
    # the sets of words that a rule's matches hold; words that rules share are looked for once
    sets = [key_words(r.pattern) for r in listed]
    strings = sorted({w for some in sets for words in some for w in words})
    place = {w: i for i, w in enumerate(strings)}
    table = constant([(i, r.label, [[place[w] for w in some] for some in sets[i]], r.pattern, r.priority, r.confidence) for i, r in enumerate(listed)], "i int, label string, words array<array<int>>, pattern string, priority int, confidence double")
    norm = F.col("norm")
    some = F.exists(constant(stems, "string"), lambda k: F.contains(norm, k))
    held = F.transform(constant(strings, "string"), lambda k: F.contains(norm, k))
    fits = lambda r: F.forall(r["words"], lambda w: F.exists(w, lambda i: F.get(F.col("held"), i)))
    two = one.withColumn("held", F.when(some, held)).withColumn("on", F.when(F.col("held").isNotNull(), F.filter(table, fits)) if gated else table)
    hit = lambda r, m: F.struct(m["s"].alias("s"), (-m["e"]).alias("to"), (-r["priority"]).alias("down"), r["i"].alias("i"), m["e"].alias("e"), r["priority"].alias("p"), (m["e"] - m["s"]).alias("len"), (-r["i"]).alias("o"), r["label"].alias("label"), r["confidence"].alias("confidence"))
    hits = F.flatten(F.transform("on", lambda r: F.transform(matches(norm, r["pattern"]), lambda m: hit(r, m))))
    three = two.withColumn("hits", hits).select("doc_id", "n_words", F.sort_array("hits").alias("hits"))
    is_base = lambda h: h["i"] < len(BASE)
    found = F.col("hits")
    four = resolved(three, is_base).withColumn("base", F.filter(found, is_base))
    names = lambda c: F.array_join(F.array_sort(F.array_distinct(F.transform(c, lambda h: h["label"]))), ",")
    return four.select(
        "doc_id",
        "n_words",
        F.coalesce(F.size("base"), F.lit(0)).cast("long").alias("n_base"),
        F.array_min(F.transform("base", lambda h: h["s"])).cast("long").alias("first_word"),
        F.array_max(F.transform("base", lambda h: h["s"])).cast("long").alias("last_word"),
        F.coalesce(names("base"), F.lit("")).alias("base_labels"),
        F.coalesce(names("kept"), F.lit("")).alias("labels"),
        F.coalesce(F.array_max(F.transform("kept", lambda h: h["confidence"])), F.lit(0.0)).alias("score"),
    )
