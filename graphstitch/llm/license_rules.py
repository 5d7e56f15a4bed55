"""License scans by ordered signature rules.

A text is lower-cased (A-Z) and reduced to its words. Four base phrases are counted at all their places. Beyond them,
hundreds of hand-written signature rules, each a regular expression over the words joined by blanks, are tried where their
keyword occurs: first a gate of a few stems for the whole text, then each rule's own keyword. A rule has a priority; detections are taken
by priority, then length, then place, and one that lies inside an interval already taken is suppressed. Places are found by
bisection, so a long text with many detections takes n log n. Base
labels stay whatever the rules say. The score is the confidence of the best detection that stands.

Defined results: null and blank texts have no words, no labels and score 0; repeated rows are each reported; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import bisect
import functools
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from graphstitch.llm.common import TERM_BYTES

#: Fixed values of the base rules: phrase and label.
BASE = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}
BASE_SCORE = 0.6

#: Stems of which one at least occurs wherever any rule can match; plain searches for these few are far cheaper than one
#: expression for all keywords.
GATE = [
    b"licen", b"gpl", b"copyright", b"spdx", b"cc0", b"cc by", b"commons", b"public domain", b"permission", b"redistribut", b"warrant", b"rights reserved", b"confidential",
    b"apache", b"software", b"fuck", b"mpl ", b"epl ", b"cddl", b"eupl", b"lppl", b"odbl", b"pddl", b"cecill", b"sspl", b"mulan", b"gfdl", b"made available", b"misrepresented",
    b"source code", b"advertising", b"buy me a beer", b"package may be copied", b"psf ", b"openssl", b"jpeg group", b"freetype", b"not evil", b"university of california",
    b"change date", b"bsd", b"wtfpl", b"as a service", b"contributing authors", b"font name", b"nasa open source", b"neither the name", b"machine executable", b"contents of this file",
]

#: Signature rules, tried in the order of their sections: "= priority confidence what", then per line the label, the keyword that
#: must occur in the text, and an expression over its words. {a|b} stands for a version, which is added to the label, and
#: so is what stands behind " + ".
RULES = r"""
= 1 0.97 sentences of license texts and of the notices that go into files
gpl ; redistribute it ; this program is free software you can redistribute it and or modify it under the terms of the gnu general public licen[sc]e
lgpl ; redistribute it ; this library is free software you can redistribute it and or modify it under the terms of the gnu (?:lesser|library) general public licen[sc]e
agpl ; redistribute it ; this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public licen[sc]e
gfdl ; permission is granted to copy ; permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation licen[sc]e
apache-2-0 ; may not use this file ; licensed under the apache licen[sc]e version 2 0 the licen[sc]e you may not use this file
apache-2-0 ; without warranties or conditions ; without warranties or conditions of any kind either express or implied see the licen[sc]e for the specific language governing permissions
apache-1-1 ; apache software foundation ; this product includes software developed by the apache software foundation
mpl-2-0 ; source code form ; this source code form is subject to the terms of the mozilla public licen[sc]e v 2 0
mpl-1-1 ; contents of this file ; the contents of this file are subject to the mozilla public licen[sc]e version 1 1
npl ; contents of this file ; the contents of this file are subject to the netscape public licen[sc]e
cddl ; contents of this file ; the contents of this file are subject to the terms of (?:either the gnu general public licen[sc]e version 2 only gpl or )?the common development and distribution licen[sc]e
epl ; accompanying materials ; this program and the accompanying materials are made available under the terms of the eclipse public licen[sc]e
cpl ; accompanying materials ; this program and the accompanying materials are made available under the terms of the common public licen[sc]e
mit ; hereby granted ; permission is hereby granted free of charge to any person obtaining a copy
mit ; permission notice ; the above copyright notice and this permission notice(?: including the next paragraph)? shall be included in all copies
mit-0 ; hereby granted ; permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so the software is provided
isc ; permission to use ; permission to use copy modify and or distribute this software for any purpose
0bsd ; permission to use ; permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted the software is provided
hpnd ; permission to use ; permission to use copy modify and distribute this software and its documentation for any purpose and without fee
bsd-3 ; neither the name ; neither the name of (?:\S+ ){1,12}nor the names of (?:its|any) contributors
bsd-4 ; advertising materials ; all advertising materials mentioning features or use of this software
bsd-2 ; redistributions ; redistributions in binary form must reproduce the above copyright notice
bsd ; redistributions ; redistributions of source code must retain the above copyright notice
bsl ; boost software ; distributed under the boost software licen[sc]e version 1 0
bsl ; machine executable ; unless such copies or derivative works are solely in the form of machine executable object code
zlib ; express or implied ; this software is provided as is without any express or implied warranty in no event will the authors
zlib ; misrepresented ; the origin of this software must not be misrepresented
libpng ; contributing authors ; the contributing authors and group 42 inc disclaim all warranties
unlicense ; unencumbered ; this is free and unencumbered software released into the public domain
cc0 ; all copyright ; to the extent possible under law (?:\S+ ){1,12}(?:has|have) waived? all copyright
cc0 ; dedicated all copyright ; dedicated all copyright and related and neighboring rights to this software to the public domain
wtfpl ; what the fuck ; you just do what the fuck you want to
beerware ; buy me a beer ; if we meet some day and you think this stuff is worth it you can buy me a beer
artistic ; conditions under which ; the intent of this document is to state the conditions under which a package may be copied
psf ; psf hereby ; psf hereby grants licensee a nonexclusive royalty free world wide licen[sc]e
openssl ; openssl toolkit ; this product includes software developed by the openssl project for use in the openssl toolkit
ssleay ; eric young ; this product includes cryptographic software written by eric young
php ; php ; this product includes php software freely available from
ofl ; font software ; this font software is licensed under the sil open font licen[sc]e
ofl ; reserved font name ; no modified version of the font software may use the reserved font name
curl ; copyright holder shall not ; except as contained in this notice the name of a copyright holder shall not be used in advertising
ijg ; independent jpeg group ; this software is based in part on the work of the independent jpeg group
freetype ; freetype ; portions of this software are copyright (?:\S+ ){0,4}the freetype project
unicode ; unicode data files ; permission is hereby granted free of charge to any person obtaining a copy of the unicode data files
w3c ; w3c ; this work is distributed under the w3c software licen[sc]e
json ; used for good ; the software shall be used for good not evil
postgresql ; university of california be liable ; in no event shall the university of california be liable to any party
tcl ; regents of the university ; this software is copyrighted by the regents of the university of california sun microsystems
ms-pl ; use the software ; if you use the software you accept this licen[sc]e if you do not accept the licen[sc]e do not use the software
sspl ; make the functionality ; if you make the functionality of the program or a modified version available to third parties as a service
busl ; change date ; effective on the change date or the fourth anniversary of the first publicly available distribution
commons-clause ; right to sell ; the grant of rights under the licen[sc]e will not include and the licen[sc]e does not grant to you the right to sell the software
elastic ; hosted or managed service ; you may not provide the software to third parties as a hosted or managed service
llama ; llama ; llama (?:\d+ )*community licen[sc]e agreement
openrail ; responsible ai ; (?:creativeml |bigscience )?(?:open )?responsible ai licen[sc]e
openrail ; rail licen ; (?:creativeml |bigscience )?(?:open )?rail licen[sc]e
= 2 0.99 identifiers
gpl ; spdx ; spdx licen[sc]e identifier gpl {1 0|2 0|3 0} or later + or-later
gpl ; spdx ; spdx licen[sc]e identifier gpl {1 0|2 0|3 0} only + only
gpl ; spdx ; spdx licen[sc]e identifier gpl {1 0|2 0|3 0}
lgpl ; spdx ; spdx licen[sc]e identifier lgpl {2 0|2 1|3 0} or later + or-later
lgpl ; spdx ; spdx licen[sc]e identifier lgpl {2 0|2 1|3 0} only + only
lgpl ; spdx ; spdx licen[sc]e identifier lgpl {2 0|2 1|3 0}
agpl ; spdx ; spdx licen[sc]e identifier agpl {1 0|3 0} or later + or-later
agpl ; spdx ; spdx licen[sc]e identifier agpl {1 0|3 0} only + only
agpl ; spdx ; spdx licen[sc]e identifier agpl {1 0|3 0}
gfdl ; spdx ; spdx licen[sc]e identifier gfdl {1 1|1 2|1 3}
apache ; spdx ; spdx licen[sc]e identifier apache {1 0|1 1|2 0}
mpl ; spdx ; spdx licen[sc]e identifier mpl {1 0|1 1|2 0}
epl ; spdx ; spdx licen[sc]e identifier epl {1 0|2 0}
cddl ; spdx ; spdx licen[sc]e identifier cddl {1 0|1 1}
eupl ; spdx ; spdx licen[sc]e identifier eupl {1 0|1 1|1 2}
osl ; spdx ; spdx licen[sc]e identifier osl {1 0|2 0|2 1|3 0}
afl ; spdx ; spdx licen[sc]e identifier afl {1 1|2 0|2 1|3 0}
artistic ; spdx ; spdx licen[sc]e identifier artistic {1 0|2 0}
ofl ; spdx ; spdx licen[sc]e identifier ofl {1 0|1 1}
bsl ; spdx ; spdx licen[sc]e identifier bsl {1 0}
bsd-2 ; spdx ; spdx licen[sc]e identifier bsd 2 clause
bsd-3 ; spdx ; spdx licen[sc]e identifier bsd 3 clause
bsd-4 ; spdx ; spdx licen[sc]e identifier bsd 4 clause
0bsd ; spdx ; spdx licen[sc]e identifier 0bsd
mit ; spdx ; spdx licen[sc]e identifier mit
mit-0 ; spdx ; spdx licen[sc]e identifier mit 0
isc ; spdx ; spdx licen[sc]e identifier isc
zlib ; spdx ; spdx licen[sc]e identifier zlib
unlicense ; spdx ; spdx licen[sc]e identifier unlicense
wtfpl ; spdx ; spdx licen[sc]e identifier wtfpl
cc0 ; spdx ; spdx licen[sc]e identifier cc0 {1 0}
cc-by ; spdx ; spdx licen[sc]e identifier cc by {1 0|2 0|2 5|3 0|4 0}
cc-by-sa ; spdx ; spdx licen[sc]e identifier cc by sa {1 0|2 0|2 5|3 0|4 0}
cc-by-nc ; spdx ; spdx licen[sc]e identifier cc by nc {1 0|2 0|2 5|3 0|4 0}
cc-by-nd ; spdx ; spdx licen[sc]e identifier cc by nd {1 0|2 0|2 5|3 0|4 0}
= 2 0.97 versions with a condition
gpl ; later ; (?:gnu general public licen[sc]e|gnu gpl|gpl) {1 0|1|2 0|2|3 0|3} (?:or|and) (?:at your option )?(?:any )?later(?: version)? + or-later
gpl ; only ; (?:gnu general public licen[sc]e|gnu gpl|gpl) {1 0|1|2 0|2|3 0|3} only + only
lgpl ; later ; (?:gnu (?:lesser|library) general public licen[sc]e|gnu lgpl|lgpl) {2 0|2 1|2|3 0|3} (?:or|and) (?:at your option )?(?:any )?later(?: version)? + or-later
lgpl ; only ; (?:gnu (?:lesser|library) general public licen[sc]e|gnu lgpl|lgpl) {2 0|2 1|2|3 0|3} only + only
agpl ; later ; (?:gnu affero general public licen[sc]e|gnu agpl|agpl) {1 0|1|3 0|3} (?:or|and) (?:at your option )?(?:any )?later(?: version)? + or-later
agpl ; only ; (?:gnu affero general public licen[sc]e|gnu agpl|agpl) {1 0|1|3 0|3} only + only
gfdl ; later ; (?:gnu free documentation licen[sc]e|gfdl) {1 1|1 2|1 3} (?:or|and) (?:any )?later(?: version)? + or-later
gfdl ; only ; (?:gnu free documentation licen[sc]e|gfdl) {1 1|1 2|1 3} only + only
mpl ; later ; (?:mozilla public licen[sc]e|mpl) {1 0|1 1|2 0} (?:or|and) (?:any )?later(?: version)? + or-later
epl ; later ; (?:eclipse public licen[sc]e|epl) {1 0|2 0} (?:or|and) (?:any )?later(?: version)? + or-later
eupl ; later ; (?:european union public licen[sc]e|eupl) {1 0|1 1|1 2} (?:or|and) (?:any )?later(?: version)? + or-later
lppl ; later ; (?:latex project public licen[sc]e|lppl) {1 0|1 2|1 3} (?:or|and) (?:any )?later(?: version)? + or-later
gpl ; classpath ; (?:gnu general public licen[sc]e|gnu gpl|gpl) {2 0|2|3 0|3} with (?:the )?classpath exception + with-classpath-exception
gpl ; linking ; (?:gnu general public licen[sc]e|gnu gpl|gpl) {2 0|2|3 0|3} with (?:a |the )?linking exception + with-linking-exception
apache ; llvm ; (?:apache licen[sc]e|apache) {2 0} with (?:the )?llvm exceptions? + with-llvm-exception
= 2 0.95 attribution licenses with their clauses
cc-by-nc-nd ; cc by ; cc by nc nd {1 0|2 0|2 5|3 0|4 0}
cc-by-nc-sa ; cc by ; cc by nc sa {1 0|2 0|2 5|3 0|4 0}
cc-by-nc ; cc by ; cc by nc {1 0|2 0|2 5|3 0|4 0}
cc-by-nd ; cc by ; cc by nd {1 0|2 0|2 5|3 0|4 0}
cc-by-sa ; cc by ; cc by sa {1 0|2 0|2 5|3 0|4 0}
cc-by ; cc by ; cc by {1 0|2 0|2 5|3 0|4 0}
cc-by-nc-nd ; creative commons ; creative commons attribution non ?commercial no ?deriv(?:ative)?s(?: works)? {1 0|2 0|2 5|3 0|4 0}(?: (?:international|unported|generic))?
cc-by-nc-sa ; creative commons ; creative commons attribution non ?commercial share ?alike {1 0|2 0|2 5|3 0|4 0}(?: (?:international|unported|generic))?
cc-by-nc ; creative commons ; creative commons attribution non ?commercial {1 0|2 0|2 5|3 0|4 0}(?: (?:international|unported|generic))?
cc-by-nd ; creative commons ; creative commons attribution no ?deriv(?:ative)?s(?: works)? {1 0|2 0|2 5|3 0|4 0}(?: (?:international|unported|generic))?
cc-by-sa ; creative commons ; creative commons attribution share ?alike {1 0|2 0|2 5|3 0|4 0}(?: (?:international|unported|generic))?
cc-by ; creative commons ; creative commons attribution {1 0|2 0|2 5|3 0|4 0}(?: (?:international|unported|generic))?
cc-by-nc-nd ; creativecommons ; creativecommons org licen[sc]es by nc nd {1 0|2 0|2 5|3 0|4 0}
cc-by-nc-sa ; creativecommons ; creativecommons org licen[sc]es by nc sa {1 0|2 0|2 5|3 0|4 0}
cc-by-nc ; creativecommons ; creativecommons org licen[sc]es by nc {1 0|2 0|2 5|3 0|4 0}
cc-by-nd ; creativecommons ; creativecommons org licen[sc]es by nd {1 0|2 0|2 5|3 0|4 0}
cc-by-sa ; creativecommons ; creativecommons org licen[sc]es by sa {1 0|2 0|2 5|3 0|4 0}
cc-by ; creativecommons ; creativecommons org licen[sc]es by {1 0|2 0|2 5|3 0|4 0}
cc0 ; creativecommons ; creativecommons org publicdomain zero {1 0}
= 3 0.92 names with a version
gpl ; general public ; gnu general public licen[sc]e {1 0|1|2 0|2|3 0|3}
gpl ; gpl ; (?:gnu )?gpl {1 0|1|2 0|2|3 0|3}
gpl ; gplv ; gplv{1|2|3} (?:or|and) (?:any )?later(?: version)? + or-later
gpl ; gplv ; gplv{1|2|3}
lgpl ; general public ; gnu (?:lesser|library) general public licen[sc]e {2 0|2 1|2|3 0|3}
lgpl ; lgpl ; (?:gnu )?lgpl {2 0|2 1|2|3 0|3}
lgpl ; lgplv ; lgplv{2 1|2|3}
agpl ; affero ; (?:gnu )?affero general public licen[sc]e {1 0|1|3 0|3}
agpl ; agpl ; (?:gnu )?agpl {1 0|1|3 0|3}
agpl ; agplv ; agplv{3}
gfdl ; free documentation ; gnu free documentation licen[sc]e {1 1|1 2|1 3}
gfdl ; gfdl ; gfdl {1 1|1 2|1 3}
apache ; apache ; apache (?:software )?licen[sc]e {1 0|1 1|2 0|2}
apache ; apache ; apache {1 0|1 1|2 0|2}
apache ; apache org licen ; www apache org licen[sc]es licen[sc]e {2 0}
mpl ; mozilla ; mozilla public licen[sc]e {1 0|1 1|2 0}
mpl ; mpl ; mpl {1 0|1 1|2 0}
epl ; eclipse ; eclipse public licen[sc]e {1 0|2 0}
epl ; epl ; epl {1 0|2 0}
edl ; eclipse ; eclipse distribution licen[sc]e {1 0}
cddl ; common development ; common development and distribution licen[sc]e {1 0|1 1}
cddl ; cddl ; cddl {1 0|1 1}
cpl ; common public ; common public licen[sc]e {1 0}
cpal ; common public attribution ; common public attribution licen[sc]e {1 0}
eupl ; european union public ; european union public licen[sc]e {1 0|1 1|1 2}
eupl ; eupl ; eupl {1 0|1 1|1 2}
osl ; open software licen ; open software licen[sc]e {1 0|2 0|2 1|3 0}
afl ; academic free ; academic free licen[sc]e {1 1|2 0|2 1|3 0}
artistic ; artistic ; (?:perl )?artistic licen[sc]e {1 0|2 0}
lppl ; latex project ; latex project public licen[sc]e {1 0|1 2|1 3}
lppl ; lppl ; lppl {1 0|1 2|1 3}
ofl ; open font ; (?:sil )?open font licen[sc]e {1 0|1 1}
bsl ; boost ; boost software licen[sc]e {1 0}
php ; php licen ; php licen[sc]e {3 0|3 01}
psf ; python software foundation ; python software foundation licen[sc]e {2 0|2}
psf ; psf licen ; psf licen[sc]e {2 0|2}
zpl ; zope ; zope public licen[sc]e {1 1|2 0|2 1}
wtfpl ; fuck ; do what the fuck you want to public licen[sc]e {2}
wtfpl ; wtfpl ; wtfpl {2}
odbl ; open database ; open database licen[sc]e {1 0}
odbl ; odbl ; odbl {1 0}
odc-by ; open data commons ; open data commons attribution licen[sc]e {1 0}
pddl ; public domain dedication ; public domain dedication and licen[sc]e {1 0}
pddl ; pddl ; pddl {1 0}
cdla ; community data licen ; community data licen[sc]e agreement (?:permissive|sharing) {1 0|2 0}
cecill ; cecill ; cecill(?: free software licen[sc]e)? {1 0|2 0|2 1}
apsl ; apple public ; apple public source licen[sc]e {1 0|1 1|1 2|2 0}
ipl ; ibm public ; ibm public licen[sc]e {1 0}
npl ; netscape public ; netscape public licen[sc]e {1 0|1 1}
sspl ; server side public ; server side public licen[sc]e {1 0|1}
sspl ; sspl ; sspl {1 0|1}
busl ; business source ; business source licen[sc]e {1 1}
elastic ; elastic licen ; elastic licen[sc]e {2 0}
rpl ; reciprocal public ; reciprocal public licen[sc]e {1 1|1 5}
upl ; universal permissive ; universal permissive licen[sc]e {1 0}
mulan ; mulan permissive ; mulan permissive software licen[sc]e {1|2}
mulan ; mulan psl ; mulan psl {1|2}
qpl ; q public ; q public licen[sc]e {1 0}
sissl ; sun industry ; sun industry standards source licen[sc]e {1 1|1 2}
spl ; sun public ; sun public licen[sc]e {1 0}
rpsl ; realnetworks ; realnetworks public source licen[sc]e {1 0}
nosa ; nasa open source ; nasa open source agreement {1 3}
ecl ; educational community ; educational community licen[sc]e {1 0|2 0}
ogl ; open government ; open government licen[sc]e {1 0|2 0|3 0}
polyform ; polyform ; polyform (?:noncommercial|small business|shield|strict) licen[sc]e {1 0 0}
blueoak ; blue oak ; blue oak model licen[sc]e {1 0 0}
cc0 ; cc0 ; cc0 {1 0}(?: universal)?
= 4 0.9 grants by name
gpl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:gnu general public licen[sc]e|gnu gpl|gpl)
lgpl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:gnu (?:lesser|library) general public licen[sc]e|gnu lgpl|lgpl)
agpl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:gnu affero general public licen[sc]e|gnu agpl|agpl)
gfdl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:gnu free documentation licen[sc]e|gfdl)
apache ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:apache software licen[sc]e|apache licen[sc]e|apache)
mit ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the |an )?(?:mit x11 licen[sc]e|x11 licen[sc]e|expat licen[sc]e|mit licen[sc]e)
bsd ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the |a )?(?:bsd licen[sc]e|bsd style licen[sc]e|berkeley software distribution licen[sc]e)
mpl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:mozilla public licen[sc]e|mpl)
epl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:eclipse public licen[sc]e|epl)
cddl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:common development and distribution licen[sc]e|cddl)
eupl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:european union public licen[sc]e|eupl)
lppl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:latex project public licen[sc]e|lppl)
psf ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:python software foundation licen[sc]e|psf licen[sc]e)
wtfpl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:do what the fuck you want to public licen[sc]e|wtfpl)
odbl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:open database licen[sc]e|odbl)
pddl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:public domain dedication and licen[sc]e|pddl)
cecill ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?cecill
sspl ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?(?:server side public licen[sc]e|sspl)
unlicense ; under ; (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of )?(?:the )?unlicense
proprietary ; under ; (?:licensed|released|distributed|available|published) under (?:a )?proprietary licen[sc]e
dual ; dual licensed ; dual licensed under
= 5 0.85 attribution licenses without a version
cc-by-nc-nd ; cc by ; cc by nc nd
cc-by-nc-sa ; cc by ; cc by nc sa
cc-by-nc ; cc by ; cc by nc
cc-by-nd ; cc by ; cc by nd
cc-by-sa ; cc by ; cc by sa
cc-by-nc-nd ; creative commons ; creative commons attribution non ?commercial no ?deriv(?:ative)?s(?: works)?
cc-by-nc-sa ; creative commons ; creative commons attribution non ?commercial share ?alike
cc-by-nc ; creative commons ; creative commons attribution non ?commercial
cc-by-nd ; creative commons ; creative commons attribution no ?deriv(?:ative)?s(?: works)?
cc-by-sa ; creative commons ; creative commons attribution share ?alike
cc-by ; creative commons ; creative commons attribution
cc0 ; cc0 ; cc0
cc0 ; creative commons ; creative commons zero
public-domain ; public domain ; (?:dedicated to|released into|placed in|in) the public domain
= 6 0.75 names
gpl ; general public ; gnu general public licen[sc]e
gpl ; gnu gpl ; gnu gpl
lgpl ; general public ; gnu (?:lesser|library) general public licen[sc]e
lgpl ; lgpl ; gnu lgpl
agpl ; affero ; gnu affero general public licen[sc]e
agpl ; agpl ; gnu agpl
gfdl ; free documentation ; gnu free documentation licen[sc]e
apache ; apache ; apache software licen[sc]e
apache ; apache ; apache licen[sc]e
mpl ; mozilla ; mozilla public licen[sc]e
epl ; eclipse ; eclipse public licen[sc]e
cddl ; common development ; common development and distribution licen[sc]e
cpl ; common public ; common public licen[sc]e
eupl ; european union public ; european union public licen[sc]e
osl ; open software licen ; open software licen[sc]e
afl ; academic free ; academic free licen[sc]e
artistic ; artistic ; (?:perl )?artistic licen[sc]e
lppl ; latex project ; latex project public licen[sc]e
ofl ; open font ; (?:sil )?open font licen[sc]e
bsl ; boost ; boost software licen[sc]e
php ; php licen ; php licen[sc]e
psf ; python software foundation ; python software foundation licen[sc]e
psf ; psf licen ; psf licen[sc]e
zpl ; zope ; zope public licen[sc]e
ncsa ; ncsa ; (?:university of illinois )?ncsa open source licen[sc]e
zlib ; zlib ; zlib (?:libpng )?licen[sc]e
isc ; isc licen ; isc licen[sc]e
wtfpl ; fuck ; do what the fuck you want to public licen[sc]e
wtfpl ; wtfpl ; wtfpl
unlicense ; unlicense ; unlicense
bsd ; bsd licen ; bsd licen[sc]e
bsd ; bsd style ; bsd style licen[sc]e
bsd ; berkeley software ; berkeley software distribution licen[sc]e
bsd-2 ; bsd 2 clause ; bsd 2 clause(?: licen[sc]e)?
bsd-3 ; bsd 3 clause ; bsd 3 clause(?: licen[sc]e)?
bsd-2 ; simplified bsd ; simplified bsd licen[sc]e
bsd-3 ; bsd licen ; (?:new|modified) bsd licen[sc]e
mit ; x11 licen ; (?:mit )?x11 licen[sc]e
mit ; expat ; expat licen[sc]e
mit ; mit licen ; mit licen[sc]e
mit ; mit style ; mit style licen[sc]e
odbl ; open database ; open database licen[sc]e
odc-by ; open data commons ; open data commons attribution licen[sc]e
pddl ; public domain dedication ; public domain dedication and licen[sc]e
cecill ; cecill ; cecill free software licen[sc]e
ms-pl ; microsoft public ; microsoft public licen[sc]e
ms-rl ; microsoft reciprocal ; microsoft reciprocal licen[sc]e
apsl ; apple public ; apple public source licen[sc]e
ipl ; ibm public ; ibm public licen[sc]e
npl ; netscape public ; netscape public licen[sc]e
sspl ; server side public ; server side public licen[sc]e
busl ; business source ; business source licen[sc]e
rpl ; reciprocal public ; reciprocal public licen[sc]e
upl ; universal permissive ; universal permissive licen[sc]e
mulan ; mulan ; mulan (?:permissive software licen[sc]e|psl)
ecl ; educational community ; educational community licen[sc]e
ogl ; open government ; open government licen[sc]e
openssl ; openssl licen ; openssl licen[sc]e
beerware ; ware licen ; (?:the )?beer ?ware licen[sc]e
json ; json licen ; json licen[sc]e
vim ; vim licen ; vim licen[sc]e
ruby ; ruby licen ; ruby licen[sc]e
proprietary ; confidential ; proprietary and confidential
= 7 0.6 bare names
cc-by ; cc by ; cc by
gpl ; gplv ; gplv\d
= 8 0.4 reservations
proprietary ; rights reserved ; all rights reserved
"""


@dataclass(frozen=True)
class Rule:
    label: str
    suffix: str
    pattern: bytes
    keyword: bytes
    priority: int
    score: float


_VERSION = re.compile(r"\{([\d |]+)\}")


def rules() -> list[Rule]:
    """All rules in order; smaller priorities are taken first."""
    out, priority, score = [], 0, 0.0
    for line in RULES.strip().splitlines():
        if line.startswith("= "):
            number, confidence, _ = line[2:].split(" ", 2)
            priority, score = int(number), float(confidence)
            continue
        label, keyword, expression = line.split(" ; ")
        suffix = ""
        if found := _VERSION.search(expression):
            expression, plus, tail = expression.partition(" + ")
            suffix = plus and "-" + tail
            # longer versions first, so that 2 0 is not taken for 2
            versions = "|".join(sorted(found.group(1).split("|"), key=len, reverse=True))
            glued = expression[: found.start()].endswith("v")
            expression = expression[: found.start()] + ("" if glued else "(?:version |v ?)?") + f"(?P<v>{versions})(?! \\d)" + expression[found.end() :]
        out.append(Rule(label, suffix, f" (?:{expression})(?= )".encode(), keyword.encode(), priority, score))
    return out


class Scanner:
    def __init__(self):
        grouped: dict[bytes, list] = {}
        for r in rules():
            grouped.setdefault(r.keyword, []).append((r, re.compile(r.pattern)))
        self.grouped = list(grouped.items())
        self.phrases = [(f" {p} ".encode(), label) for p, label in BASE.items()]

    @staticmethod
    def opens(text: bytes) -> bool:
        return any(g in text for g in GATE)

    def detections(self, text: bytes, blanks: np.ndarray) -> list[tuple[int, int, str, float]]:
        """What stands: word intervals [a, b) of a text of words between blanks, label and confidence. blanks: their places, none for a text that the gate holds back."""
        if not len(blanks):
            return []
        found = []
        for keyword, some in self.grouped:
            if keyword in text:
                for rule, pattern in some:
                    for m in pattern.finditer(text):
                        a, b = np.searchsorted(blanks, (m.start(), m.end())).tolist()
                        version = m.groupdict().get("v")
                        label = rule.label + ("-" + version.decode().replace(" ", "-") if version else "") + rule.suffix
                        found.append((rule.priority, m.start() - m.end(), a, b, label, rule.score))
        found.sort()
        # the taken intervals that lie in no other: both their starts and their ends ascend
        starts: list[int] = []
        ends: list[int] = []
        taken = []
        for _, _, a, b, label, score in found:
            i = bisect.bisect_right(starts, a)
            if i and ends[i - 1] >= b:
                continue
            taken.append((a, b, label, score))
            i = bisect.bisect_left(starts, a)
            j = bisect.bisect_right(ends, b, i)
            starts[i:j], ends[i:j] = [a], [b]
        return sorted(taken)

    def scan(self, text: str | None) -> tuple:
        words = text.encode().translate(TERM_BYTES).split() if text else []
        joined = b" " + b" ".join(words) + b" "
        at, labels = [], set()
        for phrase, label in self.phrases:
            here = joined.find(phrase)
            while here >= 0:
                at.append(here)
                labels.add(label)
                here = joined.find(phrase, here + 1)
        blanks = np.flatnonzero(np.frombuffer(joined, np.uint8) == 32) if at or self.opens(joined) else np.empty(0, np.int64)
        places = np.searchsorted(blanks, at).tolist()
        stand = self.detections(joined, blanks)
        score = max([BASE_SCORE * bool(labels), *(x[3] for x in stand)])
        every = labels | {x[2] for x in stand}
        return len(words), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(labels)), ",".join(sorted(every)), float(score)


@functools.lru_cache(1)
def scanner() -> Scanner:
    return Scanner()


COLUMNS = "n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double"


def scan(docs: DataFrame) -> DataFrame:
    """Per document: doc_id and the columns above."""

    def run(batches):
        kinds = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.float64()]
        for batch in batches:
            rows = [scanner().scan(t) for t in batch.column("text").to_pylist()]
            cols = zip(*rows) if rows else [()] * 7
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, k) for c, k in zip(cols, kinds))], ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, " + COLUMNS)
