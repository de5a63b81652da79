"""License statements in texts, by ordered rules behind a keyword filter."""

from __future__ import annotations

import re
from bisect import bisect_left
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from itertools import accumulate

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from driftview.llm.tokens import frugal, slices
from driftview.shipping import ship

# The base phrases and their labels.
BASE = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))

WORDS = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


@dataclass(frozen=True)
class Rule:
    """A pattern over words joined by single blanks; it is tried only where ``keyword`` stands."""

    label: str
    keyword: str
    pattern: str
    priority: int
    certainty: float


#: Parts that patterns share: what is said before a license's name, the word itself, a version's mark, and "or later".
_ASK = r"(?:licensed|released|distributed|available|published|provided|covered|governed|redistributed|modified|use[ds]?|modify it) (?:only )?(?:under|by|according to|subject to) (?:the )?(?:terms (?:and conditions )?(?:of|in) )?(?:the |an? )?"
PARTS = {
    "ASK": _ASK,
    "LIC": r"licen[cs]e",
    "V": r"(?:v ?|version |ver |license version |licence version )?",
    "LATER": r"(?: (?:of the license )?or (?:at your option )?(?:any )?(?:later|newer|higher)(?: versions?)?| plus)",
    "GNU": rf"(?:{_ASK})?(?:gnu )?",
    "ID": r"spdx license identifier ",
}

#: Rules in order: label | keyword | priority | certainty | pattern over words joined by single blanks.
RULES = r"""
0bsd | 0bsd | 60 | 0.99 | {ID}0bsd
0bsd | zero clause | 30 | 0.9 | (?:bsd )?zero clause (?:bsd )?{LIC}
afl | academic free | 20 | 0.8 | academic free {LIC}
afl-1.2 | academic free | 30 | 0.9 | academic free {LIC} {V}1 2
afl-2.1 | academic free | 30 | 0.9 | academic free {LIC} {V}2 1
afl-3.0 | academic free | 30 | 0.9 | academic free {LIC} {V}3 0
agpl | affero | 20 | 0.8 | {GNU}affero (?:general )?public {LIC}
agpl | agpl | 10 | 0.6 | agpl
agpl-1.0 | affero | 30 | 0.9 | affero general public {LIC} {V}1(?: 0)?
agpl-3.0 | affero | 40 | 0.95 | {GNU}affero general public {LIC} {V}3(?: 0)?
agpl-3.0 | agpl | 40 | 0.9 | agpl ?(?:v|version )?3(?: 0)?
agpl-3.0-only | agpl | 60 | 0.99 | (?:{ID})?agpl 3 0 only
agpl-3.0-or-later | affero | 50 | 0.98 | {GNU}affero general public {LIC} (?:as published by the free software foundation )?(?:either )?{V}3(?: 0)?{LATER}
agpl-3.0-or-later | agpl | 60 | 0.99 | (?:{ID})?agpl ?v?3(?: 0)? or later
apache | apache | 10 | 0.6 | apache(?: software)? {LIC}
apache | apache | 20 | 0.8 | {ASK}apache(?: software)? {LIC}
apache-1.0 | apache | 40 | 0.95 | apache(?: software)? {LIC} {V}1 0
apache-1.1 | apache | 40 | 0.95 | apache(?: software)? {LIC} {V}1 1
apache-2.0 | apache | 40 | 0.95 | apache(?: software)? {LIC} {V}2(?: 0)?
apache-2.0 | apache | 45 | 0.98 | {ASK}apache(?: software)? {LIC} {V}2(?: 0)?
apache-2.0 | apache | 35 | 0.9 | (?:{ID})?apache ?v?2(?: 0)?
apache-2.0 | apache | 40 | 0.9 | apache org licenses {LIC} 2 0(?: txt| html)?
apsl | apple public | 20 | 0.8 | apple public source {LIC}
apsl-2.0 | apple public | 30 | 0.95 | apple public source {LIC} {V}2 0
artistic | artistic | 10 | 0.6 | (?:perl )?artistic {LIC}
perl | as perl | 30 | 0.85 | (?:under )?the same terms as perl(?: 5)?(?: itself)?
artistic-1.0 | artistic | 30 | 0.9 | (?:perl )?artistic {LIC} {V}1 0
artistic-2.0 | artistic | 30 | 0.9 | (?:perl )?artistic {LIC} {V}2(?: 0)?
beerware | ware licen | 30 | 0.9 | (?:the )?beer ?ware {LIC}
beerware | buy me a beer | 20 | 0.8 | you can buy me a beer in return
bittorrent | bittorrent open | 20 | 0.9 | bittorrent open source {LIC}
blueoak-1.0.0 | blue oak | 30 | 0.95 | blue oak model {LIC}(?: {V}1 0 0)?
boost | boost software | 20 | 0.9 | boost software {LIC}
boost-1.0 | boost software | 30 | 0.95 | boost software {LIC} {V}1 0
boost-1.0 | bsl | 60 | 0.99 | {ID}bsl 1 0
bsd | bsd | 10 | 0.5 | bsd (?:style |type |like )?{LIC}
bsd | bsd | 20 | 0.8 | {ASK}bsd(?: style| type| like)?(?: {LIC})?
bsd | redistribution and use | 20 | 0.9 | redistribution and use in source and binary forms with or without modification are permitted
bsd-1 | clause | 40 | 0.9 | (?:bsd 1|bsd one) clause(?: {LIC})?|(?:1|one) clause bsd(?: {LIC})?
bsd-2 | clause | 40 | 0.9 | (?:2|two) clause (?:simplified )?bsd(?: {LIC})?|(?:{ID})?bsd 2 clause(?: {LIC})?
bsd-2 | bsd | 30 | 0.85 | (?:simplified bsd|freebsd) {LIC}
bsd-3 | clause | 40 | 0.9 | (?:3|three) clause bsd(?: {LIC})?|(?:{ID})?bsd 3 clause(?: {LIC})?
bsd-3 | bsd | 30 | 0.85 | (?:new|revised|modified) bsd {LIC}
bsd-3 | endorse or promote | 40 | 0.9 | neither the name .{1,120}? may be used to endorse or promote products
bsd-4 | clause | 40 | 0.9 | (?:4|four) clause bsd(?: {LIC})?|(?:{ID})?bsd 4 clause(?: {LIC})?
bsd-4 | bsd | 30 | 0.85 | (?:original|old) bsd {LIC}
bsd-4 | advertising materials | 40 | 0.9 | all advertising materials mentioning features or use of this software must display
busl-1.1 | business source | 30 | 0.95 | business source {LIC}(?: {V}1 1)?
cc | creative commons | 10 | 0.5 | creative commons(?: {LIC})?
cc | creative commons | 20 | 0.8 | {ASK}creative commons(?: {LIC})?
cc | creativecommons | 20 | 0.8 | creativecommons org licenses
cc0 | cc0 | 30 | 0.9 | (?:{ID})?cc0(?: {V}1 0)?(?: universal)?
cc0 | creative commons zero | 30 | 0.9 | creative commons zero(?: {V}1 0)?(?: universal)?
cc0 | cc 0 | 20 | 0.7 | cc 0(?: 1 0)?(?: universal)?
cc0 | publicdomain zero | 40 | 0.95 | creativecommons org publicdomain zero 1 0
cc0 | waived all copyright | 40 | 0.9 | waived all copyright and related or neighboring rights
cc-by | cc by | 30 | 0.8 | cc by(?! (?:sa|nd|nc)\b)
cc-by | creative commons attribution | 30 | 0.9 | creative commons attribution(?! (?:share|non|no ))(?: {LIC})?
cc-by | licenses by | 40 | 0.9 | creativecommons org licenses by(?! (?:sa|nd|nc)\b)
cc-by-1.0 | cc by | 40 | 0.9 | cc by 1 0
cc-by-2.0 | cc by | 40 | 0.9 | cc by 2 0
cc-by-2.5 | cc by | 40 | 0.9 | cc by 2 5
cc-by-3.0 | cc by | 40 | 0.9 | cc by 3 0
cc-by-3.0 | attribution 3 0 | 40 | 0.95 | creative commons attribution 3 0(?: unported| international)?(?: {LIC})?
cc-by-4.0 | cc by | 40 | 0.95 | cc by 4 0
cc-by-4.0 | attribution 4 0 | 40 | 0.95 | creative commons attribution 4 0(?: international)?(?: {LIC})?
cc-by-4.0 | licenses by 4 | 50 | 0.95 | creativecommons org licenses by 4 0
cc-by-sa | by sa | 30 | 0.85 | cc by sa
cc-by-sa | attribution share | 30 | 0.9 | creative commons attribution share ?alike(?: {LIC})?
cc-by-sa | licenses by sa | 40 | 0.9 | creativecommons org licenses by sa
cc-by-sa-2.0 | by sa 2 | 40 | 0.9 | cc by sa 2 0
cc-by-sa-3.0 | by sa 3 | 40 | 0.9 | cc by sa 3 0
cc-by-sa-3.0 | alike 3 0 | 40 | 0.95 | creative commons attribution share ?alike 3 0(?: unported)?(?: {LIC})?
cc-by-sa-4.0 | by sa 4 | 40 | 0.95 | cc by sa 4 0
cc-by-sa-4.0 | alike 4 0 | 40 | 0.95 | creative commons attribution share ?alike 4 0(?: international)?(?: {LIC})?
cc-by-nd | by nd | 30 | 0.85 | cc by nd(?: [1-4] [05])?
cc-by-nd | attribution no | 30 | 0.9 | creative commons attribution no ?deriv(?:ative)?s?(?: works)?(?: [1-4] [05])?
cc-by-nc | by nc | 30 | 0.85 | cc by nc(?! (?:sa|nd)\b)(?: [1-4] [05])?
cc-by-nc | attribution non | 30 | 0.9 | creative commons attribution non ?commercial(?! (?:share|no))(?: [1-4] [05])?
cc-by-nc-sa | by nc sa | 35 | 0.9 | cc by nc sa(?: [1-4] [05])?
cc-by-nc-sa | commercial share | 35 | 0.9 | creative commons attribution non ?commercial share ?alike(?: [1-4] [05])?
cc-by-nc-nd | by nc nd | 35 | 0.9 | cc by nc nd(?: [1-4] [05])?
cc-by-nc-nd | commercial no | 35 | 0.9 | creative commons attribution non ?commercial no ?deriv(?:ative)?s?(?: works)?(?: [1-4] [05])?
cddl | common development | 20 | 0.85 | common development and distribution {LIC}
cddl | cddl | 10 | 0.6 | cddl
cddl-1.0 | cddl | 30 | 0.9 | cddl {V}1 0
cddl-1.0 | common development | 30 | 0.95 | common development and distribution {LIC} {V}1 0
cddl-1.1 | cddl | 30 | 0.9 | cddl {V}1 1
cecill | cecill | 20 | 0.85 | cecill(?: free software)?(?: {LIC}(?: agreement)?)?
cecill-2.1 | cecill | 30 | 0.95 | cecill {V}2 1
cecill-b | cecill b | 30 | 0.95 | cecill b
cecill-c | cecill c | 30 | 0.95 | cecill c
copyright | copyright | 10 | 0.6 | copyright (?:c |© )?(?:19|20)\d\d(?: (?:19|20)\d\d)*
copyright | copyright | 10 | 0.5 | copyright (?:c|©)
copyright | © | 10 | 0.6 | © ?(?:19|20)\d\d(?: (?:19|20)\d\d)*
copyright | copyright | 10 | 0.5 | copyright (?:holders?|owners?)
cpl | common public | 20 | 0.8 | common public {LIC}
cpl-1.0 | common public | 30 | 0.9 | common public {LIC} {V}1 0
ecl-2.0 | educational community | 30 | 0.95 | educational community {LIC}(?: {V}2 0)?
elastic-2.0 | elastic licen | 30 | 0.95 | elastic {LIC}(?: {V}2(?: 0)?)?
epl | eclipse public | 20 | 0.85 | eclipse public {LIC}
epl-1.0 | eclipse public | 30 | 0.95 | eclipse public {LIC} {V}1(?: 0)?
epl-1.0 | epl 1 | 30 | 0.9 | epl 1 0
epl-2.0 | eclipse public | 30 | 0.95 | eclipse public {LIC} {V}2(?: 0)?
epl-2.0 | epl 2 | 30 | 0.9 | epl 2 0
eula | end user | 20 | 0.8 | end user {LIC} agreement
eula | agree to be bound | 20 | 0.7 | by (?:installing|copying|downloading|using)(?: or otherwise using)? (?:the|this) (?:software|product) you agree to be bound
eupl | eupl | 10 | 0.7 | eupl
eupl | european union public | 20 | 0.9 | european union public {LIC}
eupl-1.1 | eupl | 30 | 0.95 | eupl {V}1 1
eupl-1.2 | eupl | 30 | 0.95 | eupl {V}1 2
eupl-1.2 | european union public | 30 | 0.95 | european union public {LIC} {V}1 2
fair-use | fair use | 10 | 0.5 | fair use (?:policy|doctrine|of copyrighted)
ftl | freetype | 30 | 0.9 | freetype (?:project )?{LIC}
gfdl | free documentation | 20 | 0.85 | {GNU}free documentation {LIC}
gfdl | gfdl | 10 | 0.7 | gfdl
gfdl-1.1 | free documentation | 30 | 0.95 | {GNU}free documentation {LIC} {V}1 1
gfdl-1.2 | free documentation | 30 | 0.95 | {GNU}free documentation {LIC} {V}1 2
gfdl-1.3 | free documentation | 30 | 0.95 | {GNU}free documentation {LIC} {V}1 3
gfdl-1.3-or-later | free documentation | 50 | 0.98 | {GNU}free documentation {LIC} {V}1 3{LATER}
gpl | general public | 10 | 0.6 | (?:gnu )?general public {LIC}
gpl | general public | 20 | 0.85 | {ASK}(?:gnu )?general public {LIC}
gpl | gpl | 10 | 0.5 | (?:gnu )?gpl
gpl | gpl | 20 | 0.8 | {ASK}(?:gnu )?gpl
gpl | gnu org | 20 | 0.8 | gnu org (?:copyleft|licenses)(?: gpl(?: html)?)?
gpl-1.0 | general public | 40 | 0.95 | {GNU}general public {LIC} {V}1(?: 0)?
gpl-1.0-or-later | general public | 50 | 0.98 | {GNU}general public {LIC} (?:as published by the free software foundation )?(?:either )?{V}1(?: 0)?{LATER}
gpl-2.0 | general public | 40 | 0.95 | {GNU}general public {LIC} (?:as published by the free software foundation )?{V}2(?: 0)?(?: only| of the {LIC})?
gpl-2.0 | gpl | 40 | 0.9 | gpl ?(?:v|version )?2(?: 0)?
gpl-2.0-only | gpl | 60 | 0.99 | (?:{ID})?gpl ?v?2(?: 0)? only
gpl-2.0-or-later | general public | 50 | 0.98 | {GNU}general public {LIC} (?:as published by the free software foundation )?(?:either )?{V}2(?: 0)?{LATER}
gpl-2.0-or-later | gpl | 60 | 0.99 | (?:{ID})?gpl ?(?:v|version )?2(?: 0)? or(?: any)? later(?: version)?
gpl-3.0 | general public | 40 | 0.95 | {GNU}general public {LIC} (?:as published by the free software foundation )?{V}3(?: 0)?(?: only| of the {LIC})?
gpl-3.0 | gpl | 40 | 0.9 | gpl ?(?:v|version )?3(?: 0)?
gpl-3.0-only | gpl | 60 | 0.99 | (?:{ID})?gpl ?v?3(?: 0)? only
gpl-3.0-or-later | general public | 50 | 0.98 | {GNU}general public {LIC} (?:as published by the free software foundation )?(?:either )?{V}3(?: 0)?{LATER}
gpl-3.0-or-later | gpl | 60 | 0.99 | (?:{ID})?gpl ?(?:v|version )?3(?: 0)? or(?: any)? later(?: version)?
gpl-classpath | classpath exception | 40 | 0.95 | (?:with )?(?:the )?(?:gnu )?classpath exception
gpl-linking | linking exception | 30 | 0.85 | (?:with )?(?:a )?(?:static |special )?linking exception
hippocratic | hippocratic | 20 | 0.9 | hippocratic {LIC}(?: {V}\d \d)?
hpnd | historical permission | 30 | 0.9 | historical permission notice and disclaimer
icu | icu licen | 30 | 0.9 | icu {LIC}
ijg | independent jpeg | 30 | 0.9 | independent jpeg group(?: s software| {LIC})?
imagemagick | imagemagick licen | 30 | 0.9 | imagemagick {LIC}
ipl-1.0 | ibm public | 30 | 0.95 | ibm public {LIC}(?: {V}1 0)?
isc | isc licen | 20 | 0.85 | isc {LIC}
isc | identifier isc | 60 | 0.99 | {ID}isc
isc | permission to use copy | 40 | 0.9 | permission to use copy modify and or distribute this software for any purpose
json | json licen | 30 | 0.9 | json {LIC}
json | good not evil | 40 | 0.95 | software shall be used for good not evil
lgpl | lesser general | 20 | 0.85 | {GNU}lesser general public {LIC}
lgpl | library general | 20 | 0.85 | {GNU}library general public {LIC}
lgpl | lgpl | 15 | 0.7 | (?:gnu )?lgpl
lgpl-2.0 | library general | 40 | 0.95 | {GNU}library general public {LIC} {V}2(?: 0)?
lgpl-2.0-or-later | library general | 50 | 0.98 | {GNU}library general public {LIC} (?:as published by the free software foundation )?(?:either )?{V}2(?: 0)?{LATER}
lgpl-2.1 | lesser general | 40 | 0.95 | {GNU}lesser general public {LIC} {V}2 1
lgpl-2.1 | lgpl | 40 | 0.9 | lgpl ?(?:v|version )?2 1
lgpl-2.1-only | lgpl | 60 | 0.99 | (?:{ID})?lgpl ?v?2 1 only
lgpl-2.1-or-later | lesser general | 50 | 0.98 | {GNU}lesser general public {LIC} (?:as published by the free software foundation )?(?:either )?{V}2 1{LATER}
lgpl-2.1-or-later | lgpl | 60 | 0.99 | (?:{ID})?lgpl ?(?:v|version )?2 1 or(?: any)? later(?: version)?
lgpl-3.0 | lesser general | 40 | 0.95 | {GNU}lesser general public {LIC} {V}3(?: 0)?
lgpl-3.0 | lgpl | 40 | 0.9 | lgpl ?(?:v|version )?3(?: 0)?
lgpl-3.0-only | lgpl | 60 | 0.99 | (?:{ID})?lgpl ?v?3(?: 0)? only
lgpl-3.0-or-later | lesser general | 50 | 0.98 | {GNU}lesser general public {LIC} (?:as published by the free software foundation )?(?:either )?{V}3(?: 0)?{LATER}
lgpl-3.0-or-later | lgpl | 60 | 0.99 | (?:{ID})?lgpl ?(?:v|version )?3(?: 0)? or(?: any)? later(?: version)?
libpng | libpng licen | 30 | 0.9 | libpng {LIC}(?: {V}2)?
libtiff | libtiff licen | 30 | 0.9 | libtiff {LIC}
llama | llama | 30 | 0.9 | llama (?:\d(?: \d)? )?community {LIC}(?: agreement)?
lppl | latex project | 20 | 0.9 | latex project public {LIC}
lppl | lppl | 10 | 0.7 | lppl
lppl-1.3c | lppl 1 | 30 | 0.95 | lppl 1 3c?
mit | mit licen | 20 | 0.85 | mit {LIC}
mit |  mit | 25 | 0.9 | {ASK}mit(?: {LIC})?
mit | identifier mit | 60 | 0.99 | {ID}mit
mit | mit x11 | 30 | 0.9 | mit x11 {LIC}
mit | expat licen | 30 | 0.9 | expat {LIC}
mit | hereby granted | 40 | 0.95 | permission is hereby granted free of charge to any person obtaining a copy of this software
mit-0 | mit 0 | 35 | 0.95 | (?:{ID})?mit 0
mit-0 | mit no attribution | 35 | 0.95 | mit no attribution(?: {LIC})?
mpl | mozilla public | 20 | 0.85 | mozilla public {LIC}
mpl | mpl | 10 | 0.6 | mpl {LIC}
mpl-1.0 | mozilla public | 30 | 0.95 | mozilla public {LIC} {V}1 0
mpl-1.1 | mozilla public | 30 | 0.95 | mozilla public {LIC} {V}1 1
mpl-1.1 | mpl | 30 | 0.9 | mpl ?{V}1 1
mpl-2.0 | mozilla public | 30 | 0.95 | mozilla public {LIC} {V}2(?: 0)?
mpl-2.0 | mozilla public | 40 | 0.98 | (?:this source code form is )?subject to the terms of the mozilla public {LIC} v(?:ersion)? 2 0
mpl-2.0 | mpl | 30 | 0.9 | (?:{ID})?mpl ?{V}2(?: 0)?
ms-pl | microsoft public | 30 | 0.95 | microsoft public {LIC}
ms-pl | ms pl | 20 | 0.85 | ms pl
ms-rl | microsoft reciprocal | 30 | 0.95 | microsoft reciprocal {LIC}
mulanpsl-2.0 | mulan | 30 | 0.95 | mulan (?:psl|permissive software {LIC})(?: {V}2)?
ncsa | illinois ncsa | 30 | 0.95 | university of illinois ncsa open source {LIC}
odbl | database licen | 20 | 0.85 | open (?:data commons )?(?:open )?database {LIC}
odbl | odbl | 10 | 0.7 | odbl
odbl-1.0 | database licen | 30 | 0.95 | open (?:data commons )?(?:open )?database {LIC} {V}1 0
odc-by | odc by | 30 | 0.9 | odc by(?: 1 0)?
odc-by | data commons attribution | 30 | 0.95 | open data commons attribution {LIC}
ofl | open font | 20 | 0.85 | (?:sil )?open font {LIC}
ofl-1.1 | open font | 30 | 0.95 | (?:sil )?open font {LIC} {V}1 1
ofl-1.1 | ofl 1 | 30 | 0.9 | ofl 1 1
ogl | open government | 20 | 0.9 | open government {LIC}(?: {V}\d 0)?
openldap | openldap public | 30 | 0.95 | openldap public {LIC}
openssl | openssl | 20 | 0.85 | openssl {LIC}
osl | open software licen | 20 | 0.85 | open software {LIC}
osl-3.0 | open software licen | 30 | 0.95 | open software {LIC} {V}3 0
php-3.01 | php licen | 30 | 0.9 | php {LIC}(?: {V}3 0?1)?
polyform | polyform | 30 | 0.95 | polyform (?:non ?commercial|small business|shield|strict|perimeter|internal use)(?: {LIC})?(?: 1 0 0)?
postgresql | postgresql licen | 30 | 0.95 | postgresql {LIC}
proprietary | proprietary | 20 | 0.7 | (?:proprietary and confidential|confidential and proprietary)(?: information)?
proprietary | may not be | 20 | 0.8 | may not be (?:reproduced|copied|distributed|redistributed|published)(?: or \w+)* without (?:the )?(?:express |prior )*(?:written )?(?:permission|consent)
proprietary | trade secret | 10 | 0.6 | (?:contains|constitutes) (?:valuable )?trade secrets?
proprietary | unauthori | 20 | 0.7 | unauthori[sz]ed (?:copying|use|distribution|reproduction)(?: or \w+)* (?:of this \w+ )?(?:via any medium )?is (?:strictly )?prohibited
psf | python software | 20 | 0.9 | python software foundation {LIC}(?: agreement)?
psf-2.0 | python software | 30 | 0.95 | python software foundation {LIC} {V}2(?: 0)?
public-domain | public domain | 20 | 0.7 | (?:is |are |has been )?(?:hereby )?(?:released |placed |dedicated )?(?:in|into|to) the public domain
public-domain | public domain | 30 | 0.85 | (?:this (?:work|file|software|code) )is (?:in the )?public domain
qpl | q public | 30 | 0.9 | q public {LIC}(?: {V}1 0)?
rail | openrail | 30 | 0.9 | (?:bigscience |creativeml |bigcode )?openrail(?: [mds]+)?(?: {LIC})?
some-rights-reserved | some rights | 10 | 0.6 | some rights reserved
no-rights-reserved | no rights | 10 | 0.6 | no rights reserved
ruby | ruby licen | 20 | 0.8 | ruby {LIC}
ruby | ruby s licen | 20 | 0.8 | ruby s {LIC}
sleepycat | sleepycat | 30 | 0.9 | sleepycat {LIC}
sspl-1.0 | server side public | 30 | 0.95 | server side public {LIC}(?: {V}1)?
sspl-1.0 | sspl | 20 | 0.8 | sspl(?: 1 0| v1)?
terms | terms of | 10 | 0.4 | (?:subject to|agree to|bound by) (?:the |our |these )?terms of (?:service|use)
trademark | trademark | 10 | 0.4 | (?:is a |are )(?:registered )?trademarks? of
unicode | unicode | 20 | 0.85 | unicode (?:inc )?{LIC}(?: agreement)?
unlicense | unlicense | 30 | 0.95 | (?:{ID})?(?:the )?unlicense
unlicense | unencumbered | 40 | 0.95 | this is free and unencumbered software released into the public domain
upl-1.0 | universal permissive | 30 | 0.95 | universal permissive {LIC}(?: {V}1 0)?
vim | vim licen | 30 | 0.9 | vim {LIC}
w3c | w3c | 30 | 0.9 | w3c (?:software|document)(?: and document)?(?: notice and)? {LIC}
warranty | as is without | 10 | 0.5 | (?:provided |distributed )?as is without (?:any )?(?:express or implied )?warrant(?:y|ies)(?: of any kind)?
warranty | merchantability | 10 | 0.5 | implied warrant(?:y|ies) of merchantability(?: or fitness for a particular purpose)?
wtfpl | do what the | 30 | 0.95 | do what the \w+ you want to public {LIC}
wtfpl | wtfpl | 20 | 0.9 | wtfpl(?: {V}2)?
x11 | x11 licen | 20 | 0.85 | x11 {LIC}
zlib | zlib | 30 | 0.9 | zlib(?: libpng)? {LIC}
zlib | misrepresented | 40 | 0.95 | the origin of this software must not be misrepresented
zpl | zope public | 20 | 0.9 | zope public {LIC}
zpl-2.1 | zope public | 30 | 0.95 | zope public {LIC} {V}2 1
"""


def rules() -> tuple[Rule, ...]:
    """All rules in the order of the table."""
    found = []
    for line in RULES.strip().splitlines():
        label, keyword, priority, certainty, pattern = line.split(" | ", 4)
        for name, part in PARTS.items():
            pattern = pattern.replace("{" + name + "}", part)
        found.append(Rule(label, keyword, pattern, int(priority), float(certainty)))
    return tuple(found)


class Scanner:
    """Compiled rules; an automaton finds which keywords a text holds, and only their rules are tried."""

    def __init__(self, given: tuple[Rule, ...]) -> None:
        self.gated: dict[str, list[tuple[int, Rule, re.Pattern]]] = {}
        for order, r in enumerate(given):
            self.gated.setdefault(r.keyword, []).append((order, r, re.compile(rf"(?<![^ ])(?:{r.pattern})(?![^ ])")))
        self.automaton = ahocorasick.Automaton()
        for k in self.gated:
            self.automaton.add_word(k, k)
        self.automaton.make_automaton()

    def detect(self, joined: str) -> list[tuple[int, int, Rule]]:
        """Detections left when those that stand within another of no lower rank are dropped.

        Rank is priority, then length, then the rules' order.
        """
        near = {k for _, k in self.automaton.iter(joined)}
        hits = [(m.start(), m.end(), order, r) for k in near for order, r, p in self.gated[k] for m in p.finditer(joined) if m.end() > m.start()]
        if len(hits) < 2:
            return [(a, b, r) for a, b, _, r in hits]
        hits.sort(key=lambda h: (-h[3].priority, h[0] - h[1], h[2], h[0]))
        furthest = Furthest(sorted({h[0] for h in hits}))
        kept = []
        for a, b, _, r in hits:
            if furthest.upto(a) < b:  # of kept ones that begin here or before, none ends here or after
                furthest.add(a, b)
                kept.append((a, b, r))
        return sorted(kept, key=lambda h: h[:2])


class Furthest:
    """Largest end among the intervals that begin up to a place, in steps of the logarithm of their number."""

    def __init__(self, starts: list[int]) -> None:
        self.starts, self.ends = starts, [-1] * (len(starts) + 1)

    def add(self, start: int, end: int) -> None:
        k = bisect_left(self.starts, start) + 1
        while k < len(self.ends):
            self.ends[k] = max(self.ends[k], end)
            k += k & -k

    def upto(self, start: int) -> int:
        k, end = bisect_left(self.starts, start) + 1, -1
        while k:
            end = max(end, self.ends[k])
            k -= k & -k
        return end


@lru_cache(maxsize=1)
def scanner() -> Scanner:
    return Scanner(rules())


_BASE_PATTERNS = tuple((re.compile(rf"(?<= )(?={p} )"), label, p) for p, label in BASE)


def base_places(joined: str) -> list[tuple[int, str]]:
    """Start and label of each place of a base phrase; ``joined`` has blanks at both ends."""
    return [(m.start(), label) for pattern, label, phrase in _BASE_PATTERNS if phrase in joined for m in pattern.finditer(joined)]


def license_scan(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """License statements of each text: (doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, detections).

    Rules read a text's words, A-Z in lower case, joined by single blanks.  A
    rule is tried only if its keyword stands in the text; of overlapping
    detections, one within another of no lower rank is dropped.  Base phrases
    are sought apart from the rules, at all their places, and their labels
    always stay.  ``score`` is the largest certainty of what was found, 1 with a
    base phrase.  ``detections`` holds label, first word and number of words.

    A null or empty text has no words: counts 0, no first and last word, empty
    labels, score 0.  Whole texts of any length are read.  Repeated rows and
    null ids are scanned each.  An empty table gives an empty result; other
    columns are ignored.
    """
    ship(docs.sparkSession)
    kind = docs.schema[doc_id].dataType.simpleString()
    one = pa.struct([("label", pa.string()), ("word", pa.int64()), ("n_words", pa.int64())])
    fields = [("n_words", pa.int64()), ("n_base", pa.int64()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64()), ("detections", pa.list_(one))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scan = scanner()
        for batch in batches:
            for part in slices(batch, "text"):
                rows = [_scanned(scan, x) for x in part.column("text").to_pylist()]
                columns = [pa.array(list(c), t) for c, (_, t) in zip(zip(*rows, strict=True), fields, strict=True)]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *columns], ["doc_id", *(n for n, _ in fields)])

    return docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(frugal(run), f"doc_id {kind}, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, detections array<struct<label: string, word: long, n_words: long>>")


def _scanned(scan: Scanner, text: str | None) -> tuple:
    text = text or ""
    words = WORDS.findall(text.lower() if text.isascii() else text.translate(_LOWER))
    joined = f" {' '.join(words)} "
    base = base_places(joined)
    found = scan.detect(joined)
    if not base and not found:
        return len(words), 0, None, None, "", "", 0.0, []
    begins = list(accumulate((len(w) + 1 for w in words), initial=1))  # of each word in ``joined``
    number = lambda at: bisect_left(begins, at)
    at = [number(a) for a, _ in base]
    base_labels = {label for _, label in base}
    labels = base_labels | {r.label for _, _, r in found}
    score = 1.0 if base else max(r.certainty for _, _, r in found)
    detections = [{"label": r.label, "word": number(a), "n_words": number(b + 1) - number(a)} for a, b, r in found]
    return len(words), len(base), min(at, default=None), max(at, default=None), ",".join(sorted(base_labels)), ",".join(sorted(labels)), score, detections
