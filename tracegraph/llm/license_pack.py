"""The signature rules of the license scan, written out one a line: label | keyword | confidence | expression.

Expressions run over words in lower case with single spaces between them ("GPL-3.0" reads "gpl 3 0"). The keyword is a
plain string that every match holds; a rule is tried only where it occurs. More confident rules come first, then longer matches,
then the order here.
"""

from __future__ import annotations

RULES = r"""
apache-2.0 | apache | 1.0 | licen[sc]ed under the apache licen[sc]e version 2 0 the licen[sc]e
apache-2.0 | apache | 0.98 | apache (?:software )?licen[sc]e (?:v|version )?2(?: 0)?
apache-2.0 | apache | 0.95 | apache ?v?2(?: 0)?
apache-2.0 | apache | 0.95 | apache licen[sc]e 2 0
apache-2.0 | apache org | 1.0 | (?:https? )?(?:www )?apache org licenses license 2 0(?: txt| html)?
apache-1.1 | apache | 0.97 | apache (?:software )?licen[sc]e (?:v|version )?1 1
apache-1.1 | apache software foundation | 0.9 | this product includes software developed by the apache software foundation
apache-1.0 | apache | 0.97 | apache (?:software )?licen[sc]e (?:v|version )?1 0
apache | apache | 0.8 | apache (?:software )?licen[sc]e
apache | apache | 0.75 | (?:under|with) (?:the )?apache (?:terms|conditions)
mit | permission is hereby granted | 1.0 | permission is hereby granted free of charge to any person obtaining a copy of this software
mit | permission is hereby granted | 0.95 | permission is hereby granted free of charge to any person
mit | the above copyright notice | 0.9 | the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software
mit | mit licen | 0.95 | (?:the )?mit licen[sc]e
mit | mit x11 | 0.9 | mit x11(?: licen[sc]e)?
mit | x11 licen | 0.85 | x11 licen[sc]e
mit | expat licen | 0.9 | expat licen[sc]e
mit | under mit | 0.8 | (?:licen[sc]ed|released|distributed|available) under mit
mit | license mit | 0.85 | licen[sc]e mit
mit | opensource org licenses mit | 1.0 | (?:https? )?(?:www )?opensource org licenses mit(?: license)?(?: php| html)?
mit-0 | mit no attribution | 0.97 | mit no attribution(?: licen[sc]e)?
mit-0 | mit 0 | 0.8 | licen[sc]e mit 0
bsd-2-clause | 2 clause | 0.97 | (?:bsd 2 clause|2 clause bsd)(?: licen[sc]e)?
bsd-2-clause | simplified bsd | 0.95 | simplified bsd(?: licen[sc]e)?
bsd-2-clause | freebsd licen | 0.93 | freebsd licen[sc]e
bsd-3-clause | 3 clause | 0.97 | (?:bsd 3 clause|3 clause bsd)(?: licen[sc]e)?
bsd-3-clause | new bsd | 0.93 | new bsd(?: licen[sc]e)?
bsd-3-clause | modified bsd | 0.93 | modified bsd(?: licen[sc]e)?
bsd-3-clause | revised bsd | 0.93 | revised bsd(?: licen[sc]e)?
bsd-3-clause | to endorse or promote | 0.9 | may be used to endorse or promote products derived from this software without specific prior written permission
bsd-4-clause | 4 clause | 0.97 | (?:bsd 4 clause|4 clause bsd)(?: licen[sc]e)?
bsd-4-clause | advertising materials | 0.9 | all advertising materials mentioning features or use of this software must display the following acknowledg[e]?ment
bsd-zero | zero clause | 0.95 | (?:bsd zero clause|zero clause bsd)(?: licen[sc]e)?
bsd-zero | 0bsd | 0.95 | 0bsd(?: licen[sc]e)?
bsd | redistribution and use | 1.0 | redistribution and use in source and binary forms with or without modification are permitted
bsd | redistribution and use | 0.95 | redistribution and use in source and binary forms
bsd | redistributions | 0.85 | redistributions (?:of source code must retain|in binary form must reproduce) the above copyright notice
bsd | bsd licen | 0.9 | (?:the )?bsd licen[sc]e
bsd | bsd style | 0.8 | bsd style(?: licen[sc]e)?
bsd | under bsd | 0.75 | (?:licen[sc]ed|released|distributed|available) under bsd
bsd | berkeley software distribution | 0.7 | berkeley software distribution
gpl-1.0 | gpl | 0.95 | (?:gnu )?gpl ?(?:v|version|ver)? ?1(?: 0)?
gpl-2.0 | gpl | 0.95 | (?:gnu )?gpl ?(?:v|version|ver)? ?2(?: 0)?
gpl-2.0+ | gpl | 0.97 | (?:gnu )?gpl ?(?:v|version|ver)? ?2(?: 0)? or (?:any )?(?:later|newer)(?: version)?
gpl-2.0-only | gpl | 0.97 | (?:gnu )?gpl ?(?:v|version|ver)? ?2(?: 0)? only
gpl-3.0 | gpl | 0.95 | (?:gnu )?gpl ?(?:v|version|ver)? ?3(?: 0)?
gpl-3.0+ | gpl | 0.97 | (?:gnu )?gpl ?(?:v|version|ver)? ?3(?: 0)? or (?:any )?(?:later|newer)(?: version)?
gpl-3.0-only | gpl | 0.97 | (?:gnu )?gpl ?(?:v|version|ver)? ?3(?: 0)? only
gpl-2.0 | general public licen | 0.97 | (?:gnu )?general public licen[sc]e (?:as published by the free software foundation )?(?:either )?(?:v|version )2(?: 0)?
gpl-3.0 | general public licen | 0.97 | (?:gnu )?general public licen[sc]e (?:as published by the free software foundation )?(?:either )?(?:v|version )3(?: 0)?
gpl-2.0+ | any later version | 0.98 | general public licen[sc]e as published by the free software foundation either version 2 of the licen[sc]e or at your option any later version
gpl-3.0+ | any later version | 0.98 | general public licen[sc]e as published by the free software foundation either version 3 of the licen[sc]e or at your option any later version
gpl | gnu general public | 0.9 | gnu general public licen[sc]e
gpl | general public licen | 0.85 | general public licen[sc]e
gpl | under the gpl | 0.85 | (?:licen[sc]ed |released |distributed |available )?under the gpl
gpl | under gpl | 0.85 | (?:licen[sc]ed|released|distributed|available) under gpl
gpl | gpl licen | 0.85 | (?:gnu )?gpl licen[sc]ed?
gpl | gnu gpl | 0.8 | gnu gpl
gpl | gpl compatible | 0.5 | gpl compatible
gpl | gnu org licenses gpl | 1.0 | (?:https? )?(?:www )?gnu org licenses gpl(?: (?:1|2|3) 0)?(?: txt| html)?
gpl | free software you can redistribute | 0.8 | this (?:program|library|file) is free software you can redistribute it and or modify it
gpl-classpath | classpath exception | 0.9 | (?:gpl )?(?:with )?classpath exception
gpl-linking | linking exception | 0.7 | (?:gpl )?(?:with )?(?:a )?(?:special )?linking exception
lgpl-2.0 | lgpl | 0.95 | (?:gnu )?lgpl ?(?:v|version|ver)? ?2(?: 0)?
lgpl-2.1 | lgpl | 0.96 | (?:gnu )?lgpl ?(?:v|version|ver)? ?2 1
lgpl-2.1+ | lgpl | 0.98 | (?:gnu )?lgpl ?(?:v|version|ver)? ?2 1 or (?:any )?(?:later|newer)(?: version)?
lgpl-3.0 | lgpl | 0.95 | (?:gnu )?lgpl ?(?:v|version|ver)? ?3(?: 0)?
lgpl-3.0+ | lgpl | 0.97 | (?:gnu )?lgpl ?(?:v|version|ver)? ?3(?: 0)? or (?:any )?(?:later|newer)(?: version)?
lgpl-2.1 | lesser general public | 0.97 | (?:gnu )?lesser general public licen[sc]e (?:as published by the free software foundation )?(?:either )?(?:v|version )2 1
lgpl-3.0 | lesser general public | 0.97 | (?:gnu )?lesser general public licen[sc]e (?:as published by the free software foundation )?(?:either )?(?:v|version )3(?: 0)?
lgpl-2.0 | library general public | 0.95 | (?:gnu )?library general public licen[sc]e(?: (?:v|version )2(?: 0)?)?
lgpl | lesser general public | 0.92 | (?:gnu )?lesser general public licen[sc]e
lgpl | lgpl | 0.8 | (?:gnu )?lgpl(?: licen[sc]ed?)?
lgpl | gnu org licenses lgpl | 1.0 | (?:https? )?(?:www )?gnu org licenses lgpl(?: (?:2|3) [01])?(?: txt| html)?
agpl-3.0 | agpl | 0.96 | (?:gnu )?agpl ?(?:v|version|ver)? ?3(?: 0)?(?: only| or later)?
agpl-1.0 | affero | 0.95 | affero general public licen[sc]e (?:v|version )?1(?: 0)?
agpl-3.0 | affero | 0.97 | (?:gnu )?affero general public licen[sc]e (?:v|version )?3(?: 0)?
agpl | affero | 0.92 | (?:gnu )?affero (?:general public )?licen[sc]e
agpl | agpl | 0.8 | (?:gnu )?agpl(?: licen[sc]ed?)?
fdl-1.1 | free documentation | 0.97 | (?:gnu )?free documentation licen[sc]e (?:v|version )?1 1
fdl-1.2 | free documentation | 0.97 | (?:gnu )?free documentation licen[sc]e (?:v|version )?1 2
fdl-1.3 | free documentation | 0.97 | (?:gnu )?free documentation licen[sc]e (?:v|version )?1 3
fdl | free documentation | 0.9 | (?:gnu )?free documentation licen[sc]e
fdl | gfdl | 0.85 | (?:gnu )?gfdl(?: 1 [123])?
fdl | invariant sections | 0.8 | with no invariant sections no front cover texts and no back cover texts
mpl-1.0 | mozilla public | 0.97 | mozilla public licen[sc]e (?:v|version )?1 0
mpl-1.1 | mozilla public | 0.97 | mozilla public licen[sc]e (?:v|version )?1 1
mpl-2.0 | mozilla public | 0.97 | mozilla public licen[sc]e (?:v|version )?2(?: 0)?
mpl-2.0 | mozilla org mpl | 1.0 | (?:https? )?(?:www )?mozilla org mpl(?: 2 0)?
mpl-2.0 | mpl | 0.93 | mpl ?(?:v|version )?2(?: 0)?
mpl-1.1 | mpl | 0.93 | mpl ?(?:v|version )?1 1
mpl | mozilla public | 0.9 | mozilla public licen[sc]e
npl | netscape public | 0.9 | netscape public licen[sc]e(?: (?:v|version )?1 [01])?
epl-1.0 | eclipse public | 0.97 | eclipse public licen[sc]e (?:v|version )?1 0
epl-2.0 | eclipse public | 0.97 | eclipse public licen[sc]e (?:v|version )?2 0
epl | eclipse public | 0.9 | eclipse public licen[sc]e
epl-1.0 | epl | 0.9 | epl ?v?1 0
epl-2.0 | epl | 0.9 | epl ?v?2 0
edl | eclipse distribution | 0.9 | eclipse distribution licen[sc]e(?: (?:v|version )?1 0)?
cddl-1.0 | common development and distribution | 0.97 | common development and distribution licen[sc]e (?:cddl )?(?:v|version )?1 0
cddl-1.1 | common development and distribution | 0.97 | common development and distribution licen[sc]e (?:cddl )?(?:v|version )?1 1
cddl | common development and distribution | 0.9 | common development and distribution licen[sc]e
cddl | cddl | 0.8 | cddl(?: (?:v|version )?1 [01])?
cpl-1.0 | common public licen | 0.9 | common public licen[sc]e(?: (?:v|version )?1 0)?
cpal-1.0 | common public attribution | 0.95 | common public attribution licen[sc]e(?: (?:v|version )?1 0)?
ipl-1.0 | ibm public | 0.95 | ibm public licen[sc]e(?: (?:v|version )?1 0)?
isc | permission to use copy modify | 1.0 | permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted
isc | permission to use copy modify | 0.95 | permission to use copy modify and or distribute this software for any purpose
isc | isc licen | 0.93 | isc licen[sc]e
isc | internet systems consortium | 0.6 | internet (?:systems|software) consortium
hpnd | permission to use copy modify | 0.85 | permission to use copy modify and distribute this software and its documentation for any purpose
artistic-1.0 | artistic licen | 0.95 | artistic licen[sc]e (?:v|version )?1 0
artistic-2.0 | artistic licen | 0.95 | artistic licen[sc]e (?:v|version )?2 0
artistic | artistic licen | 0.88 | (?:perl )?artistic licen[sc]e
perl | same terms as perl | 0.9 | under the same terms as perl itself
zlib | zlib licen | 0.92 | zlib licen[sc]e
zlib | zlib libpng | 0.92 | zlib libpng(?: licen[sc]e)?
zlib | altered source versions | 0.9 | altered source versions must be plainly marked as such and must not be misrepresented
zlib | in no event will the authors | 0.7 | in no event will the authors be held liable for any damages arising from the use of this software
libpng | libpng licen | 0.9 | libpng licen[sc]e(?: (?:v|version )?2)?
boost-1.0 | boost software | 0.97 | boost software licen[sc]e (?:v|version )?1 0
boost | boost software | 0.92 | boost software licen[sc]e
boost-1.0 | bsl 1 0 | 0.85 | bsl 1 0
busl-1.1 | business source | 0.93 | business source licen[sc]e(?: (?:v|version )?1 1)?
sspl-1.0 | server side public | 0.95 | server side public licen[sc]e(?: (?:v|version )?1(?: 0)?)?
elastic-2.0 | elastic licen | 0.93 | elastic licen[sc]e(?: (?:v|version )?2(?: 0)?)?
eupl-1.1 | european union public | 0.97 | european union public licen[sc]e (?:v|version )?1 1
eupl-1.2 | european union public | 0.97 | european union public licen[sc]e (?:v|version )?1 2
eupl | european union public | 0.9 | european union public licen[sc]e
eupl | eupl | 0.8 | eupl(?: (?:v|version )?1 [012])?
cecill | cecill | 0.9 | (?:licence )?cecill(?: [bc])?(?: (?:v|version )?[12](?: [01])?)?
odbl-1.0 | open database licen | 0.95 | (?:odc )?open database licen[sc]e(?: (?:v|version )?1 0)?
odbl | odbl | 0.85 | odbl(?: (?:v|version )?1 0)?
odc-by | open data commons attribution | 0.95 | open data commons attribution licen[sc]e(?: (?:v|version )?1 0)?
pddl | public domain dedication and licen | 0.95 | (?:open data commons )?public domain dedication and licen[sc]e
cdla-permissive | community data license agreement | 0.9 | community data license agreement permissive(?: (?:v|version )?[12] 0)?
cdla-sharing | community data license agreement | 0.9 | community data license agreement sharing(?: (?:v|version )?1 0)?
ogl-uk | open government licen | 0.92 | (?:uk )?open government licen[sc]e(?: (?:v|version )?[123] 0)?
ofl-1.1 | open font licen | 0.95 | (?:sil )?open font licen[sc]e (?:v|version )?1 1
ofl | open font licen | 0.9 | (?:sil )?open font licen[sc]e
ofl-1.1 | ofl 1 1 | 0.9 | ofl 1 1
unlicense | unlicense | 0.9 | (?:the )?unlicense
unlicense | unencumbered software | 0.97 | this is free and unencumbered software released into the public domain
unlicense | unlicense org | 1.0 | (?:https? )?unlicense org
wtfpl | wtfpl | 0.9 | wtfpl(?: (?:v|version )?2)?
wtfpl | do what the fuck you want | 0.95 | do what the fuck you want to(?: public licen[sc]e)?
beerware | beer ware | 0.9 | (?:the )?beer ware licen[sc]e
beerware | beerware | 0.85 | beerware(?: licen[sc]e)?
blueoak-1.0 | blue oak | 0.95 | blue oak model licen[sc]e(?: 1 0 0)?
upl-1.0 | universal permissive | 0.95 | universal permissive licen[sc]e(?: (?:v|version )?1 0)?
ncsa | university of illinois | 0.9 | university of illinois (?:ncsa )?open source licen[sc]e
postgresql | postgresql licen | 0.93 | postgresql licen[sc]e
python-2.0 | python software foundation | 0.9 | python software foundation licen[sc]e(?: (?:v|version )?2)?
php-3.01 | php licen | 0.9 | php licen[sc]e(?: (?:v|version )?3 01)?
ruby | ruby licen | 0.85 | ruby licen[sc]e
vim | vim licen | 0.85 | vim licen[sc]e
openssl | openssl licen | 0.9 | openssl licen[sc]e
openssl | openssl toolkit | 0.8 | for use in the openssl toolkit
w3c | w3c software | 0.9 | w3c software (?:and document )?(?:notice and )?licen[sc]e
qpl-1.0 | q public licen | 0.95 | q public licen[sc]e(?: (?:v|version )?1 0)?
ms-pl | microsoft public | 0.95 | microsoft public licen[sc]e
ms-rl | microsoft reciprocal | 0.95 | microsoft reciprocal licen[sc]e
afl-3.0 | academic free | 0.93 | academic free licen[sc]e(?: (?:v|version )?3 0)?
osl-3.0 | open software licen | 0.93 | open software licen[sc]e(?: (?:v|version )?3 0)?
apsl-2.0 | apple public source | 0.95 | apple public source licen[sc]e(?: (?:v|version )?2 0)?
sunpro | sun microsystems | 0.6 | developed at sunpro a sun microsystems inc business
intel | intel open source | 0.9 | intel open source licen[sc]e
lppl | latex project public | 0.95 | latex project public licen[sc]e(?: (?:v|version )?1 [0123])?
mulan-2 | mulan permissive | 0.95 | mulan permissive software licen[sc]e(?: (?:v|version )?[12])?
ecl-2.0 | educational community | 0.95 | educational community licen[sc]e(?: (?:v|version )?2 0)?
cc-by-1.0 | cc by 1 0 | 0.97 | cc by 1 0
cc-by-2.0 | cc by 2 0 | 0.97 | cc by 2 0
cc-by-2.5 | cc by 2 5 | 0.97 | cc by 2 5
cc-by-3.0 | cc by 3 0 | 0.97 | cc by 3 0
cc-by-4.0 | cc by 4 0 | 0.97 | cc by 4 0
cc-by-sa-2.0 | cc by sa 2 0 | 0.98 | cc by sa 2 0
cc-by-sa-2.5 | cc by sa 2 5 | 0.98 | cc by sa 2 5
cc-by-sa-3.0 | cc by sa 3 0 | 0.98 | cc by sa 3 0
cc-by-sa-4.0 | cc by sa 4 0 | 0.98 | cc by sa 4 0
cc-by-nc-3.0 | cc by nc 3 0 | 0.98 | cc by nc 3 0
cc-by-nc-4.0 | cc by nc 4 0 | 0.98 | cc by nc 4 0
cc-by-nd-3.0 | cc by nd 3 0 | 0.98 | cc by nd 3 0
cc-by-nd-4.0 | cc by nd 4 0 | 0.98 | cc by nd 4 0
cc-by-nc-sa-3.0 | cc by nc sa 3 0 | 0.99 | cc by nc sa 3 0
cc-by-nc-sa-4.0 | cc by nc sa 4 0 | 0.99 | cc by nc sa 4 0
cc-by-nc-nd-3.0 | cc by nc nd 3 0 | 0.99 | cc by nc nd 3 0
cc-by-nc-nd-4.0 | cc by nc nd 4 0 | 0.99 | cc by nc nd 4 0
cc-by | cc by | 0.9 | cc by
cc-by-sa | cc by sa | 0.94 | cc by sa
cc-by-nc | cc by nc | 0.94 | cc by nc
cc-by-nd | cc by nd | 0.94 | cc by nd
cc-by-nc-sa | cc by nc sa | 0.96 | cc by nc sa
cc-by-nc-nd | cc by nc nd | 0.96 | cc by nc nd
cc-by-4.0 | creative commons attribution | 0.97 | creative commons attribution (?:4 0 international|international 4 0)(?: licen[sc]e)?
cc-by-3.0 | creative commons attribution | 0.97 | creative commons attribution 3 0 unported(?: licen[sc]e)?
cc-by-sa-4.0 | creative commons attribution | 0.98 | creative commons attribution share ?alike 4 0(?: international)?(?: licen[sc]e)?
cc-by-sa-3.0 | creative commons attribution | 0.98 | creative commons attribution share ?alike 3 0(?: unported)?(?: licen[sc]e)?
cc-by-sa | creative commons attribution | 0.95 | creative commons attribution share ?alike(?: licen[sc]e)?
cc-by-nc | creative commons attribution | 0.95 | creative commons attribution non ?commercial(?: licen[sc]e)?
cc-by-nc-sa | creative commons attribution | 0.97 | creative commons attribution non ?commercial share ?alike(?: licen[sc]e)?
cc-by-nc-nd | creative commons attribution | 0.97 | creative commons attribution non ?commercial no ?deriv(?:s|atives)(?: works)?(?: licen[sc]e)?
cc-by-nd | creative commons attribution | 0.95 | creative commons attribution no ?deriv(?:s|atives)(?: licen[sc]e)?
cc-by | creative commons attribution | 0.92 | creative commons attribution(?: licen[sc]e)?
cc-by | creativecommons org | 1.0 | (?:https? )?creativecommons org licenses by(?: [1-4] [05])?
cc-by-sa | creativecommons org | 1.0 | (?:https? )?creativecommons org licenses by sa(?: [1-4] [05])?
cc-by-nc | creativecommons org | 1.0 | (?:https? )?creativecommons org licenses by nc(?: [1-4] [05])?
cc-by-nd | creativecommons org | 1.0 | (?:https? )?creativecommons org licenses by nd(?: [1-4] [05])?
cc-by-nc-sa | creativecommons org | 1.0 | (?:https? )?creativecommons org licenses by nc sa(?: [1-4] [05])?
cc-by-nc-nd | creativecommons org | 1.0 | (?:https? )?creativecommons org licenses by nc nd(?: [1-4] [05])?
cc0 | cc0 | 0.95 | cc0(?: 1 0)?(?: universal)?
cc0 | creative commons zero | 0.95 | creative commons zero(?: (?:v|version )?1 0)?
cc0 | creativecommons org publicdomain | 1.0 | (?:https? )?creativecommons org publicdomain zero(?: 1 0)?
cc | creative commons | 0.7 | (?:under (?:a )?)?creative commons(?: licen[sc]e)?
spdx | spdx license identifier | 0.9 | spdx license identifier [a-z0-9]+
public-domain | public domain | 0.8 | (?:in|into|to) the public domain
public-domain | public domain | 0.9 | (?:dedicated|released|placed|contributed) (?:in|into|to) the public domain
public-domain | public domain | 0.6 | public domain (?:work|software|dedication|mark)
reserved | rights reserved | 0.8 | all rights reserved
reserved-some | rights reserved | 0.7 | some rights reserved
reserved-none | rights reserved | 0.7 | no rights reserved
reserved | alle rechte vorbehalten | 0.8 | alle rechte vorbehalten
reserved | droits r | 0.8 | tous droits r(?:eserves|éservés)
reserved | derechos reservados | 0.8 | todos los derechos reservados
reserved | diritti riservati | 0.8 | tutti i diritti riservati
copyright | copyright | 0.7 | copyright(?: c)? [0-9]{4}(?: [0-9]{4})?
copyright | copyright | 0.72 | copyright(?: c)? [0-9]{4} by [^ ]+
copyright | copyright | 0.5 | copyright (?:by|holders?|owners?|notice)
copyright | copyrighted | 0.55 | copyrighted (?:material|work|by)
copyright | urheberrecht | 0.5 | urheberrechtlich gesch(?:ützt|uetzt)
warranty | warrant | 0.45 | without warranty of any kind(?: express or implied)?
warranty | warrant | 0.4 | (?:without any|without|no) warrant(?:y|ies)
warranty | merchantability | 0.5 | (?:implied )?warrant(?:y|ies) of merchantability(?: (?:and|or) fitness for a particular purpose)?
warranty | as is | 0.4 | provided (?:by the (?:authors|copyright holders) )?as is
liability | liable | 0.4 | (?:shall|will) (?:not )?be (?:held )?liable for any (?:claim )?damages
proprietary | proprietary and confidential | 0.8 | proprietary and confidential
proprietary | proprietary licen | 0.8 | proprietary licen[sc]e
proprietary | trade secret | 0.6 | (?:contains|constitutes?) (?:valuable )?trade secrets?
proprietary | unauthori | 0.7 | unauthori[sz]ed (?:copying|use|distribution|reproduction)
proprietary | strictly prohibited | 0.6 | (?:copying|distribution|reproduction) (?:is|are) strictly prohibited
proprietary | may not be reproduced | 0.7 | may not be reproduced(?: (?:or|distributed|transmitted))*
proprietary | prior written | 0.5 | without (?:the )?(?:express )?prior written (?:permission|consent)
commercial | commercial licen | 0.6 | commercial licen[sc]e
commercial | non commercial use | 0.6 | (?:for )?non commercial use only
commercial | personal use only | 0.6 | for personal use only
commercial | end user licen | 0.75 | end user licen[sc]e agreement
commercial | evaluation licen | 0.6 | evaluation licen[sc]e
responsible-ai | rail | 0.85 | (?:open|bigscience|creativeml open) rail(?: [ms])?(?: licen[sc]e)?
other-license | licen | 0.3 | (?:see|read) (?:the )?(?:licen[sc]e|licen[sc]ing) (?:file|text|terms|for details)
other-license | terms of the licen | 0.35 | (?:under|subject to) the terms of the licen[sc]e
"""


def lines() -> list[tuple[str, str, float, str]]:
    """label, keyword, confidence and expression of every rule."""
    rows = [[x.strip() for x in line.split(" | ", 3)] for line in RULES.strip().split("\n")]
    return [(label, keyword, float(confidence), expression) for label, keyword, confidence, expression in rows]
