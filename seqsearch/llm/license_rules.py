"""Hand-written license signatures, a line each: label | kind | pattern over words with single blanks.

Kinds: id (machine-readable tags), grant (a sentence that licenses), url, text (a clause of the license itself), title (its
name), name (its short name), hint (a word that only suggests one).
"""

from __future__ import annotations

LINES = """
mit | id | spdx license identifier mit
mit | id | license osi approved mit license
mit | grant | (?:licensed|released|distributed|available|published|provided) under (?:the )?(?:terms of (?:the )?)?mit(?: licen[cs]e)?
mit | grant | under the terms of the mit licen[cs]e
mit | grant | (?:is )?mit licensed
mit | title | (?:the )?mit licen[cs]e
mit | title | (?:the )?expat licen[cs]e
mit | title | licen[cs]e mit
mit | url | opensource org licenses mit(?: license)?
mit | url | mit license org
mit | text | permission is hereby granted free of charge to any person obtaining a copy
mit | text | the above copyright notice and this permission notice shall be included in all copies
mit | text | in no event shall the authors or copyright holders be liable for any claim damages or other liability
mit | text | to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense
mit | text | the software is provided as is without warranty of any kind express or implied
mit-0 | id | spdx license identifier mit 0
mit-0 | title | mit no attribution(?: licen[cs]e)?
mit-0 | name | mit 0
x11 | id | spdx license identifier x11
x11 | title | (?:mit )?x11 licen[cs]e
x11 | text | except as contained in this notice the name of the x consortium shall not be used in advertising
isc | id | spdx license identifier isc
isc | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?isc(?: licen[cs]e)?
isc | title | (?:the )?isc licen[cs]e
isc | url | opensource org licenses isc(?: license)?
isc | text | permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted
isc | text | the software is provided as is and the author disclaims all warranties with regard to this software
0bsd | id | spdx license identifier 0bsd
0bsd | title | (?:bsd )?zero clause bsd(?: licen[cs]e)?
0bsd | name | 0bsd
bsd-2-clause | id | spdx license identifier bsd 2 clause(?: patent)?
bsd-2-clause | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?(?:bsd 2 clause|2 clause bsd|simplified bsd)(?: licen[cs]e)?
bsd-2-clause | title | (?:the )?bsd 2 clause(?: licen[cs]e)?
bsd-2-clause | title | (?:the )?(?:2|two) clause bsd(?: licen[cs]e)?
bsd-2-clause | title | (?:the )?simplified bsd licen[cs]e
bsd-2-clause | title | (?:the )?freebsd licen[cs]e
bsd-2-clause | url | opensource org licenses bsd 2 clause
bsd-3-clause | id | spdx license identifier bsd 3 clause(?: clear)?
bsd-3-clause | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?(?:bsd 3 clause|3 clause bsd|new bsd|modified bsd|revised bsd)(?: licen[cs]e)?
bsd-3-clause | title | (?:the )?bsd 3 clause(?: licen[cs]e)?
bsd-3-clause | title | (?:the )?(?:3|three) clause bsd(?: licen[cs]e)?
bsd-3-clause | title | (?:the )?(?:new|modified|revised) bsd licen[cs]e
bsd-3-clause | url | opensource org licenses bsd 3 clause
bsd-3-clause | text | neither the name of [^ ]+(?: [^ ]+){0,11} nor the names of its contributors may be used to endorse or promote products
bsd-3-clause | text | neither the name of [^ ]+(?: [^ ]+){0,11} nor the names of its contributors
bsd-4-clause | id | spdx license identifier bsd 4 clause(?: uc)?
bsd-4-clause | title | (?:the )?(?:original|old) bsd licen[cs]e
bsd-4-clause | title | (?:the )?bsd 4 clause(?: licen[cs]e)?
bsd-4-clause | title | (?:the )?(?:4|four) clause bsd(?: licen[cs]e)?
bsd-4-clause | text | all advertising materials mentioning features or use of this software
bsd | grant | (?:licensed|released|distributed|available) under (?:the |a )?(?:terms of the )?bsd(?: style)?(?: licen[cs]e)?
bsd | title | (?:the )?(?:berkeley )?bsd(?: style)? licen[cs]e
bsd | id | license osi approved bsd license
bsd | url | opensource org licenses bsd license
bsd | text | redistribution and use in source and binary forms with or without modification are permitted
bsd | text | redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer
bsd | text | redistributions in binary form must reproduce the above copyright notice this list of conditions
bsd | text | this software is provided by the (?:copyright holders and contributors|regents and contributors|author) as is and any express or implied warranties
apache-2 | id | spdx license identifier apache 2 0
apache-2 | id | license osi approved apache software license
apache-2 | grant | (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?apache (?:software )?licen[cs]e (?:v|version |v )?2(?: 0)?(?: the license)?
apache-2 | grant | (?:licensed|released|distributed|available|published) under (?:the )?apache (?:v)?2(?: 0)?(?: licen[cs]e)?
apache-2 | title | (?:the )?apache (?:software )?licen[cs]e (?:v|version |v )?2(?: 0)?
apache-2 | title | apache 2(?: 0)? licen[cs]e
apache-2 | title | (?:apache|asl) v2(?: 0)?(?: licen[cs]e)?
apache-2 | name | apache 2 0
apache-2 | name | asl 2 0
apache-2 | url | www apache org licenses license 2 0(?: html| txt)?
apache-2 | url | opensource org licenses apache 2 0
apache-2 | text | you may not use this file except in compliance with the license
apache-2 | text | unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis
apache-2 | text | each contributor hereby grants to you a perpetual worldwide non exclusive no charge royalty free irrevocable copyright license
apache-2 | text | licensed to the apache software foundation asf under one or more contributor license agreements
apache-1.1 | id | spdx license identifier apache 1 1
apache-1.1 | title | (?:the )?apache (?:software )?licen[cs]e (?:v|version |v )?1 1
apache-1.1 | text | this product includes software developed by the apache (?:software foundation|group)
apache-1.0 | id | spdx license identifier apache 1 0
apache-1.0 | title | (?:the )?apache (?:software )?licen[cs]e (?:v|version |v )?1 0
apache | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?apache(?: software)?(?: licen[cs]e)?
apache | title | (?:the )?apache (?:software |public )?licen[cs]e
gpl-1 | id | spdx license identifier gpl 1 0(?: only| or later)?
gpl-1 | title | (?:the )?(?:gnu )?general public licen[cs]e (?:v|version |v )?1(?: 0)?(?: or (?:at your option )?(?:any )?later(?: version)?)?
gpl-1 | name | gpl v1
gpl-1 | name | gplv1
gpl-2 | id | spdx license identifier gpl 2 0(?: only| or later)?
gpl-2 | id | license osi approved gnu general public license v2(?: gplv2)?
gpl-2 | grant | (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?(?:gnu )?(?:general public licen[cs]e|gpl) (?:v|version |v )?2(?: 0)?(?: or (?:at your option )?(?:any )?later(?: version)?| only)?
gpl-2 | grant | (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?(?:gnu )?gplv2(?: only| or later)?
gpl-2 | title | (?:the )?(?:gnu )?general public licen[cs]e (?:v|version |v )?2(?: 0)?(?: or (?:at your option )?(?:any )?later(?: version)?| only)?
gpl-2 | name | (?:gnu )?gpl (?:v|version |v )?2(?: 0)?(?: or later| only)?
gpl-2 | name | (?:gnu )?gplv2(?: or later| only)?
gpl-2 | url | www gnu org licenses (?:old licenses )?gpl 2 0(?: html| txt| en html)?
gpl-2 | text | either version 2 of the license or at your option any later version
gpl-2 | text | gnu general public license version 2 june 1991
gpl-3 | id | spdx license identifier gpl 3 0(?: only| or later)?
gpl-3 | id | license osi approved gnu general public license v3(?: or later)?(?: gplv3)?
gpl-3 | grant | (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?(?:gnu )?(?:general public licen[cs]e|gpl) (?:v|version |v )?3(?: 0)?(?: or (?:at your option )?(?:any )?later(?: version)?| only)?
gpl-3 | grant | (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?(?:gnu )?gplv3(?: only| or later)?
gpl-3 | title | (?:the )?(?:gnu )?general public licen[cs]e (?:v|version |v )?3(?: 0)?(?: or (?:at your option )?(?:any )?later(?: version)?| only)?
gpl-3 | name | (?:gnu )?gpl (?:v|version |v )?3(?: 0)?(?: or later| only)?
gpl-3 | name | (?:gnu )?gplv3(?: or later| only)?
gpl-3 | url | www gnu org licenses gpl 3 0(?: html| txt| en html)?
gpl-3 | text | either version 3 of the license or at your option any later version
gpl-3 | text | gnu general public license version 3 29 june 2007
gpl | id | license osi approved gnu general public license gpl
gpl | grant | (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?(?:gnu )?(?:general public licen[cs]e|gpl)
gpl | title | (?:the )?(?:gnu )?general public licen[cs]e
gpl | hint | (?:gnu )?gpl
gpl | url | www gnu org (?:licenses|copyleft) gpl(?: html)?
gpl | text | this program is free software you can redistribute it and or modify it under the terms of the gnu general public license
gpl | text | this program is free software you can redistribute it and or modify it
gpl | text | you should have received a copy of the gnu general public license along with this program
gpl | text | this program is distributed in the hope that it will be useful but without any warranty
lgpl-2 | id | spdx license identifier lgpl 2 0(?: only| or later)?
lgpl-2 | title | (?:the )?(?:gnu )?library general public licen[cs]e(?: (?:v|version |v )?2(?: 0)?)?
lgpl-2 | name | (?:gnu )?lgpl (?:v|version |v )?2(?: 0)?(?: or later| only)?
lgpl-2 | name | (?:gnu )?lgplv2(?: or later| only)?
lgpl-2.1 | id | spdx license identifier lgpl 2 1(?: only| or later)?
lgpl-2.1 | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?(?:gnu )?(?:lesser general public licen[cs]e|lgpl) (?:v|version |v )?2 1
lgpl-2.1 | title | (?:the )?(?:gnu )?lesser general public licen[cs]e (?:v|version |v )?2 1(?: or (?:at your option )?(?:any )?later(?: version)?| only)?
lgpl-2.1 | name | (?:gnu )?lgpl (?:v|version |v )?2 1(?: or later| only)?
lgpl-2.1 | name | (?:gnu )?lgplv2 1(?: or later| only)?
lgpl-2.1 | url | www gnu org licenses (?:old licenses )?lgpl 2 1(?: html| txt| en html)?
lgpl-3 | id | spdx license identifier lgpl 3 0(?: only| or later)?
lgpl-3 | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?(?:gnu )?(?:lesser general public licen[cs]e|lgpl) (?:v|version |v )?3(?: 0)?
lgpl-3 | title | (?:the )?(?:gnu )?lesser general public licen[cs]e (?:v|version |v )?3(?: 0)?(?: or (?:at your option )?(?:any )?later(?: version)?| only)?
lgpl-3 | name | (?:gnu )?lgpl (?:v|version |v )?3(?: 0)?(?: or later| only)?
lgpl-3 | name | (?:gnu )?lgplv3(?: or later| only)?
lgpl-3 | url | www gnu org licenses lgpl 3 0(?: html| txt| en html)?
lgpl | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?(?:gnu )?(?:lesser general public licen[cs]e|lgpl)
lgpl | title | (?:the )?(?:gnu )?lesser general public licen[cs]e
lgpl | hint | (?:gnu )?lgpl
lgpl | text | this library is free software you can redistribute it and or modify it under the terms of the gnu (?:lesser|library) general public license
agpl-1 | id | spdx license identifier agpl 1 0(?: only| or later)?
agpl-3 | id | spdx license identifier agpl 3 0(?: only| or later)?
agpl-3 | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?(?:gnu )?(?:affero general public licen[cs]e|agpl) (?:v|version |v )?3(?: 0)?
agpl-3 | title | (?:the )?(?:gnu )?affero general public licen[cs]e (?:v|version |v )?3(?: 0)?(?: or (?:at your option )?(?:any )?later(?: version)?| only)?
agpl-3 | name | (?:gnu )?agpl (?:v|version |v )?3(?: 0)?(?: or later| only)?
agpl-3 | name | (?:gnu )?agplv3(?: or later| only)?
agpl-3 | url | www gnu org licenses agpl 3 0(?: html| txt| en html)?
agpl-3 | text | gnu affero general public license version 3 19 november 2007
agpl | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?(?:gnu )?(?:affero general public licen[cs]e|agpl)
agpl | title | (?:the )?(?:gnu )?affero general public licen[cs]e
agpl | hint | (?:gnu )?agpl
sspl-1 | id | spdx license identifier sspl 1 0
sspl-1 | title | (?:the )?server side public licen[cs]e
gfdl | id | spdx license identifier gfdl 1 [123](?: only| or later| invariants only| no invariants only)?
gfdl | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?(?:gnu )?(?:free documentation licen[cs]e|gfdl)
gfdl | title | (?:the )?(?:gnu )?free documentation licen[cs]e(?: (?:v|version |v )?1 [123])?
gfdl | text | permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation license
gfdl | name | gfdl(?: 1 [123])?
mpl-1.0 | id | spdx license identifier mpl 1 0
mpl-1.1 | id | spdx license identifier mpl 1 1
mpl-1.1 | title | (?:the )?mozilla public licen[cs]e (?:v|version |v )?1 1
mpl-1.1 | text | the contents of this file are subject to the mozilla public license version 1 1
mpl-1.1 | name | mpl (?:v)?1 1
mpl-2 | id | spdx license identifier mpl 2 0(?: no copyleft exception)?
mpl-2 | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?(?:mozilla public licen[cs]e|mpl) (?:v|version |v )?2(?: 0)?
mpl-2 | title | (?:the )?mozilla public licen[cs]e (?:v|version |v )?2(?: 0)?
mpl-2 | name | mpl (?:v)?2(?: 0)?
mpl-2 | text | this source code form is subject to the terms of the mozilla public license v 2 0
mpl-2 | url | mozilla org (?:en us )?mpl 2 0
mpl | title | (?:the )?mozilla public licen[cs]e
epl-1 | id | spdx license identifier epl 1 0
epl-1 | title | (?:the )?eclipse public licen[cs]e (?:v|version |v )?1(?: 0)?
epl-1 | url | www eclipse org legal epl v10(?: html)?
epl-2 | id | spdx license identifier epl 2 0
epl-2 | title | (?:the )?eclipse public licen[cs]e (?:v|version |v )?2(?: 0)?
epl-2 | url | www eclipse org legal epl (?:2 0|v20)(?: html)?
epl | title | (?:the )?eclipse public licen[cs]e
epl | text | this program and the accompanying materials are made available under the terms of the eclipse public license
edl-1 | title | eclipse distribution licen[cs]e(?: (?:v|version |v )?1(?: 0)?)?
cddl-1 | id | spdx license identifier cddl 1 0
cddl-1 | title | (?:the )?common development and distribution licen[cs]e(?: cddl)?(?: (?:v|version |v )?1(?: 0)?)?
cddl-1 | text | the contents of this file are subject to the terms of the common development and distribution license
cddl-1 | name | cddl(?: (?:v)?1 0)?
cddl-1.1 | id | spdx license identifier cddl 1 1
cddl-1.1 | title | (?:the )?common development and distribution licen[cs]e(?: cddl)? (?:v|version |v )?1 1
cpl-1 | id | spdx license identifier cpl 1 0
cpl-1 | title | (?:the )?common public licen[cs]e(?: (?:v|version |v )?1(?: 0)?)?
ipl-1 | title | ibm public licen[cs]e(?: (?:v|version |v )?1(?: 0)?)?
eupl | id | spdx license identifier eupl 1 [012]
eupl | title | (?:the )?european union public licen[cs]e(?: (?:v|version |v )?1 [012])?
eupl | name | eupl(?: (?:v)?1 [012])?
osl-3 | id | spdx license identifier osl 3 0
osl-3 | title | (?:the )?open software licen[cs]e (?:v|version |v )?3(?: 0)?
osl | title | (?:the )?open software licen[cs]e
afl-3 | id | spdx license identifier afl 3 0
afl-3 | title | (?:the )?academic free licen[cs]e (?:v|version |v )?3(?: 0)?
afl | title | (?:the )?academic free licen[cs]e
artistic-1 | id | spdx license identifier artistic 1 0(?: perl)?
artistic-1 | title | (?:the )?artistic licen[cs]e (?:v|version |v )?1(?: 0)?
artistic-2 | id | spdx license identifier artistic 2 0
artistic-2 | title | (?:the )?artistic licen[cs]e (?:v|version |v )?2(?: 0)?
artistic | title | (?:the )?(?:perl )?artistic licen[cs]e
artistic | text | under the same terms as perl itself
lppl | id | spdx license identifier lppl 1 [0123][ac]?
lppl | title | (?:the )?latex project public licen[cs]e(?: (?:v|version |v )?1 [0123][ac]?)?
ofl-1.1 | id | spdx license identifier ofl 1 [01](?: rfn| no rfn)?
ofl-1.1 | title | (?:the )?(?:sil )?open font licen[cs]e(?: (?:v|version |v )?1 [01])?
ofl-1.1 | text | this font software is licensed under the sil open font license
zpl | id | spdx license identifier zpl [12] [01]
zpl | title | (?:the )?zope public licen[cs]e(?: zpl)?(?: (?:v|version |v )?[12](?: [01])?)?
php-3 | id | spdx license identifier php 3 0[1]?
php-3 | title | (?:the )?php licen[cs]e(?: (?:v|version |v )?3(?: 0[1]?)?)?
php-3 | text | this source file is subject to version 3 0[1]? of the php license
python-2 | id | spdx license identifier (?:psf 2 0|python 2 0)
python-2 | title | (?:the )?python software foundation licen[cs]e(?: (?:v|version |v )?2)?
python-2 | title | (?:the )?psf licen[cs]e(?: agreement)?
boost-1 | id | spdx license identifier bsl 1 0
boost-1 | grant | distributed under the boost software license version 1 0
boost-1 | title | (?:the )?boost software licen[cs]e(?: (?:v|version |v )?1(?: 0)?)?
boost-1 | url | www boost org license 1 0 txt
busl-1.1 | id | spdx license identifier busl 1 1
busl-1.1 | title | (?:the )?business source licen[cs]e(?: 1 1)?
elastic-2 | id | spdx license identifier elastic 2 0
elastic-2 | title | (?:the )?elastic licen[cs]e(?: (?:v|version |v )?2(?: 0)?)?
ms-pl | id | spdx license identifier ms pl
ms-pl | title | (?:the )?microsoft public licen[cs]e(?: ms pl)?
ms-rl | id | spdx license identifier ms rl
ms-rl | title | (?:the )?microsoft reciprocal licen[cs]e(?: ms rl)?
zlib | id | spdx license identifier zlib
zlib | grant | (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?zlib(?: libpng)?(?: licen[cs]e)?
zlib | title | (?:the )?zlib(?: libpng)? licen[cs]e
zlib | text | the origin of this software must not be misrepresented
zlib | text | altered source versions must be plainly marked as such and must not be misrepresented as being the original software
libpng | title | (?:the )?libpng licen[cs]e
libpng | title | (?:the )?png reference library licen[cs]e
openssl | id | spdx license identifier openssl
openssl | title | (?:the )?openssl licen[cs]e
openssl | text | this product includes software developed by the openssl project
ncsa | id | spdx license identifier ncsa
ncsa | title | (?:the )?(?:university of illinois )?ncsa(?: open source)? licen[cs]e
postgresql | id | spdx license identifier postgresql
postgresql | title | (?:the )?postgresql licen[cs]e
vim | id | spdx license identifier vim
vim | title | (?:the )?vim licen[cs]e
ruby | id | spdx license identifier ruby
ruby | title | (?:the )?ruby licen[cs]e
w3c | id | spdx license identifier w3c
w3c | title | (?:the )?w3c(?: software(?: notice and)?| document)? licen[cs]e
json | id | spdx license identifier json
json | title | (?:the )?json licen[cs]e
json | text | the software shall be used for good not evil
curl | id | spdx license identifier curl
curl | title | (?:the )?curl licen[cs]e
blueoak-1 | id | spdx license identifier blueoak 1 0 0
blueoak-1 | title | (?:the )?blue oak model licen[cs]e
unlicense | id | spdx license identifier unlicense
unlicense | title | (?:the )?unlicense
unlicense | title | (?:the )?unlicence
unlicense | grant | this is free and unencumbered software released into the public domain
unlicense | url | unlicense org
wtfpl | id | spdx license identifier wtfpl
wtfpl | title | do what the fuck you want to public licen[cs]e
wtfpl | name | wtfpl
beerware | id | spdx license identifier beerware
beerware | title | (?:the )?beerware licen[cs]e
beerware | title | (?:the )?beer ware licen[cs]e
public-domain | grant | (?:released|placed|dedicated) (?:in|into|to) the public domain
public-domain | title | public domain (?:dedication|work)
public-domain | text | the author disclaims copyright to this source code
cc0-1.0 | id | spdx license identifier cc0 1 0
cc0-1.0 | title | creative commons (?:zero|cc0)(?: (?:v)?1 0)?(?: universal)?
cc0-1.0 | name | cc0(?: 1 0)?(?: universal)?
cc0-1.0 | url | creativecommons org publicdomain zero 1 0
cc-pdm-1.0 | url | creativecommons org publicdomain mark 1 0
cc-pdm-1.0 | title | public domain mark(?: 1 0)?
cc-by | id | spdx license identifier cc by [1234] [05]
cc-by | title | creative commons attribution(?: [1234] [05])?(?: international| unported| generic)?(?: public)?(?: licen[cs]e)?
cc-by | name | cc by(?: [1234] [05])?
cc-by | url | creativecommons org licenses by [1234] [05]
cc-by-sa | id | spdx license identifier cc by sa [1234] [05]
cc-by-sa | title | creative commons attribution share ?alike(?: [1234] [05])?(?: international| unported| generic)?(?: public)?(?: licen[cs]e)?
cc-by-sa | name | cc by sa(?: [1234] [05])?
cc-by-sa | url | creativecommons org licenses by sa [1234] [05]
cc-by-nc | id | spdx license identifier cc by nc [1234] [05]
cc-by-nc | title | creative commons attribution non ?commercial(?: [1234] [05])?(?: international| unported| generic)?(?: public)?(?: licen[cs]e)?
cc-by-nc | name | cc by nc(?: [1234] [05])?
cc-by-nc | url | creativecommons org licenses by nc [1234] [05]
cc-by-nd | id | spdx license identifier cc by nd [1234] [05]
cc-by-nd | title | creative commons attribution no ?deriv(?:ative)?s?(?: works)?(?: [1234] [05])?(?: international| unported| generic)?(?: public)?(?: licen[cs]e)?
cc-by-nd | name | cc by nd(?: [1234] [05])?
cc-by-nd | url | creativecommons org licenses by nd [1234] [05]
cc-by-nc-sa | id | spdx license identifier cc by nc sa [1234] [05]
cc-by-nc-sa | title | creative commons attribution non ?commercial share ?alike(?: [1234] [05])?(?: international| unported| generic)?(?: public)?(?: licen[cs]e)?
cc-by-nc-sa | name | cc by nc sa(?: [1234] [05])?
cc-by-nc-sa | url | creativecommons org licenses by nc sa [1234] [05]
cc-by-nc-nd | id | spdx license identifier cc by nc nd [1234] [05]
cc-by-nc-nd | title | creative commons attribution non ?commercial no ?deriv(?:ative)?s?(?: works)?(?: [1234] [05])?(?: international| unported| generic)?(?: public)?(?: licen[cs]e)?
cc-by-nc-nd | name | cc by nc nd(?: [1234] [05])?
cc-by-nc-nd | url | creativecommons org licenses by nc nd [1234] [05]
cc | grant | (?:licensed|released|distributed|available) under (?:a|the) creative commons licen[cs]e
cc | hint | creative commons
odbl-1 | id | spdx license identifier odbl 1 0
odbl-1 | title | (?:the )?open (?:data commons open )?database licen[cs]e(?: odbl)?(?: (?:v)?1 0)?
odc-by-1 | title | open data commons attribution licen[cs]e(?: (?:v)?1 0)?
pddl-1 | title | (?:open data commons )?public domain dedication and licen[cs]e
ogl-3 | title | open government licen[cs]e(?: v3 0)?
openrail | title | (?:creativeml |bigscience )?openrail(?: m)?(?: licen[cs]e)?
openrail | title | (?:creativeml |bigscience )?open rail(?: m)? licen[cs]e
openrail | title | responsible ai licen[cs]e
llama | title | llama (?:2|3|3 1 )?community licen[cs]e(?: agreement)?
proprietary | text | proprietary and confidential
proprietary | text | unauthorized copying of this file via any medium is strictly prohibited
proprietary | text | no part of this (?:publication|work|document) may be reproduced(?: stored| distributed)
proprietary | text | for internal use only
proprietary | title | end user licen[cs]e agreement
non-commercial | grant | for non ?commercial use only
non-commercial | text | may not be used for commercial purposes
research-only | grant | for (?:academic|research) (?:use|purposes) only
all-rights-reserved | hint | all rights reserved
all-rights-reserved | hint | alle rechte vorbehalten
all-rights-reserved | hint | tous droits réservés
all-rights-reserved | hint | todos los derechos reservados
other-license | hint | licen[cs]ed under
"""
