"""Signatures of licences: one a line, `label priority reliability [keyword] regex`.

Regexes read normalised words (ASCII lower case, one space between words). Every match holds the keyword.
Higher priority wins where one detection lies inside another: wording of the licence itself 70 and up,
machine-readable tags 60, grants 40 and 50, versions 30, bare names 10 and up.
"""

#: Hand-written signatures.
SIGNATURES = r"""
mit 70 1.0 [hereby granted] permission is hereby granted free of charge to any person obtaining a copy of this software
mit 72 1.0 [without restriction] to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense
mit 70 0.9 [permission notice] the above copyright notice and this permission notice (?:including the next paragraph )?shall be included in all copies
mit 70 0.7 [noninfringement] fitness for a particular purpose and noninfringement in no event shall the authors or copyright holders be liable
mit 60 1.0 [spdx] spdx licen[sc]e identifier mit
mit-0 61 1.0 [spdx] spdx licen[sc]e identifier mit 0
mit-0 40 0.9 [attribution] mit no attribution licen[sc]e
mit 50 0.95 [mit] (?:licensed|released|distributed|available|published|provided) under (?:the )?(?:terms of the )?mit(?: x11)? licen[sc]e
mit 48 0.9 [mit] licen[sc]e mit
mit 12 0.7 [mit] (?:the )?mit licen[sc]ed?
mit 12 0.7 [expat] expat licen[sc]e
x11 12 0.7 [x11] x11 licen[sc]e
x11 71 0.9 [consortium] except as contained in this notice the name of the x consortium shall not be used
bsd 70 1.0 [redistributions] redistributions of source code must retain the above copyright notice
bsd 70 1.0 [redistributions] redistributions in binary form must reproduce the above copyright notice
bsd 68 0.8 [redistribution] redistribution and use in source and binary forms with or without modification are permitted
bsd-3-clause 75 1.0 [endorse] neither the names? of .{1,80}? may be used to endorse or promote products derived from this software
bsd-4-clause 76 1.0 [advertising] all advertising materials mentioning features or use of this software must display
bsd-2-clause 60 1.0 [spdx] spdx licen[sc]e identifier bsd 2 clause
bsd-3-clause 60 1.0 [spdx] spdx licen[sc]e identifier bsd 3 clause
0bsd 60 1.0 [spdx] spdx licen[sc]e identifier 0bsd
bsd-2-clause 30 0.9 [bsd] (?:bsd 2 clause|2 clause bsd|simplified bsd) licen[sc]e
bsd-2-clause 30 0.8 [freebsd] freebsd licen[sc]e
bsd-3-clause 30 0.9 [bsd] (?:bsd 3 clause|3 clause bsd|(?:new|modified|revised) bsd) licen[sc]e
bsd-4-clause 30 0.9 [bsd] (?:bsd 4 clause|4 clause bsd|(?:original|old) bsd) licen[sc]e
bsd 50 0.95 [bsd] (?:licensed|released|distributed|available|published) under (?:the |a )?(?:terms of the )?bsd(?: style)? licen[sc]e
bsd 10 0.6 [bsd] bsd licen[sc]e
bsd-3-clause-clear 77 1.0 [patent] no express or implied licenses to any party s patent rights are granted by this license
bsd-2-clause-patent 77 1.0 [perpetual] each copyright holder and contributor hereby grants to those receiving rights under this license a perpetual worldwide
isc 70 1.0 [permission to use] permission to use copy modify and (?:or )?distribute this software for any purpose with or without fee is hereby granted
isc 60 1.0 [spdx] spdx licen[sc]e identifier isc
isc 50 0.95 [isc] (?:licensed|released|distributed|available) under (?:the )?(?:terms of the )?isc licen[sc]e
isc 10 0.6 [isc] isc licen[sc]e
0bsd 71 0.9 [permission to use] permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted the software is provided as is
hpnd 70 0.9 [permission to use] permission to use copy modify and distribute this software and its documentation for any purpose and without fee is hereby granted
ntp 60 1.0 [spdx] spdx licen[sc]e identifier ntp
apache 70 1.0 [in compliance] you may not use this (?:file|software|work) except in compliance with the license
apache-2.0 72 1.0 [apache] licensed under the apache licen[sc]e version 2 0(?: the license)?
apache-2.0 71 1.0 [apache] apache org licenses license 2 0
apache-2.0 60 1.0 [spdx] spdx licen[sc]e identifier apache 2 0
apache-1.1 60 1.0 [spdx] spdx licen[sc]e identifier apache 1 1
apache-1.1 74 0.9 [apache] this product includes software developed by the apache software foundation
apache-2.0 70 0.9 [contributor] subject to the terms and conditions of this license each contributor hereby grants to you a perpetual worldwide non exclusive no charge royalty free irrevocable (?:copyright|patent) license
apache-2.0 50 1.0 [apache] (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?apache (?:software )?licen[sc]e (?:version |v)?2(?: 0)?
apache 45 0.95 [apache] (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?apache (?:software )?licen[sc]e
apache-2.0 30 0.9 [apache] apache (?:software )?licen[sc]e (?:version |v)?2(?: 0)?
apache-1.1 30 0.9 [apache] apache (?:software )?licen[sc]e (?:version |v)?1 1
apache-1.0 30 0.9 [apache] apache (?:software )?licen[sc]e (?:version |v)?1 0
apache 10 0.6 [apache] apache (?:software )?licen[sc]e
gpl 70 1.0 [free software] this program is free software you can redistribute it and or modify it under the terms of the gnu general public license
gpl 70 1.0 [free software] .{1,40}? is free software you can redistribute it and or modify it under the terms of the gnu general public license
gpl-3.0 80 1.0 [general public] gnu general public license as published by the free software foundation either version 3
gpl-2.0 80 1.0 [general public] gnu general public license as published by the free software foundation either version 2
gpl-2.0-only 81 1.0 [general public] gnu general public license version 2 only
gpl 70 0.8 [general public] you should have received a copy of the gnu general public license along with this
gpl-3.0 75 0.9 [tivoization] protection against tivoization
gpl-3.0 70 0.9 [copyleft] the gnu general public license is a free copyleft license for software and other kinds of works
gpl-2.0 70 0.9 [general public] the licenses for most software are designed to take away your freedom to share and change it by contrast the gnu general public license
gpl-2.0-only 60 1.0 [spdx] spdx licen[sc]e identifier gpl 2 0 only
gpl-2.0-or-later 60 1.0 [spdx] spdx licen[sc]e identifier gpl 2 0 or later
gpl-3.0-only 60 1.0 [spdx] spdx licen[sc]e identifier gpl 3 0 only
gpl-3.0-or-later 60 1.0 [spdx] spdx licen[sc]e identifier gpl 3 0 or later
gpl-2.0 59 1.0 [spdx] spdx licen[sc]e identifier gpl 2 0
gpl-3.0 59 1.0 [spdx] spdx licen[sc]e identifier gpl 3 0
gpl-3.0-or-later 52 1.0 [later] gnu (?:general public licen[sc]e|gpl) (?:version |v)?3(?: 0)? or (?:at your option )?(?:any )?later(?: version)?
gpl-2.0-or-later 52 1.0 [later] gnu (?:general public licen[sc]e|gpl) (?:version |v)?2(?: 0)? or (?:at your option )?(?:any )?later(?: version)?
gpl-3.0 30 0.9 [gnu] gnu (?:general public licen[sc]e|gpl) (?:version |v)?3(?: 0)?
gpl-2.0 30 0.9 [gnu] gnu (?:general public licen[sc]e|gpl) (?:version |v)?2(?: 0)?
gpl-1.0 30 0.9 [gnu] gnu (?:general public licen[sc]e|gpl) (?:version |v)?1(?: 0)?
gpl-3.0 31 0.85 [gplv3] (?:the )?gplv3
gpl-2.0 31 0.85 [gplv2] (?:the )?gplv2
gpl 45 0.95 [general public] (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?gnu general public licen[sc]e
gpl 45 0.9 [gpl] (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?(?:gnu )?gpl
gpl 10 0.6 [general public] gnu general public licen[sc]e
gpl 10 0.6 [gpl] gnu gpl
gpl-classpath-exception 82 1.0 [linking] linking this library statically or dynamically with other modules is making a combined work based on this library
lgpl 71 1.0 [free software] this library is free software you can redistribute it and or modify it under the terms of the gnu (?:lesser|library) general public license
lgpl-2.1 80 1.0 [lesser] gnu lesser general public license as published by the free software foundation either version 2 1
lgpl-3.0 80 1.0 [lesser] gnu lesser general public license as published by the free software foundation either version 3
lgpl-2.0 80 1.0 [library] gnu library general public license as published by the free software foundation either version 2
lgpl 72 0.8 [lesser] you should have received a copy of the gnu lesser general public license along with this
lgpl-2.1-only 60 1.0 [spdx] spdx licen[sc]e identifier lgpl 2 1 only
lgpl-2.1-or-later 60 1.0 [spdx] spdx licen[sc]e identifier lgpl 2 1 or later
lgpl-3.0-only 60 1.0 [spdx] spdx licen[sc]e identifier lgpl 3 0 only
lgpl-3.0-or-later 60 1.0 [spdx] spdx licen[sc]e identifier lgpl 3 0 or later
lgpl-2.1 32 0.9 [lesser] gnu lesser general public licen[sc]e (?:version |v)?2 1
lgpl-3.0 32 0.9 [lesser] gnu lesser general public licen[sc]e (?:version |v)?3(?: 0)?
lgpl-2.0 32 0.9 [library] gnu library general public licen[sc]e (?:version |v)?2(?: 0)?
lgpl 46 0.95 [lesser] (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?gnu lesser general public licen[sc]e
lgpl 14 0.6 [lesser] gnu lesser general public licen[sc]e
lgpl 14 0.6 [library] gnu library general public licen[sc]e
lgpl 12 0.6 [lgpl] (?:gnu )?lgpl
agpl 73 1.0 [affero] (?:under the terms of the )?gnu affero general public license as published by the free software foundation
agpl-3.0 81 1.0 [affero] gnu affero general public license as published by the free software foundation either version 3
agpl-3.0 76 0.9 [interacting] all users interacting with it remotely through a computer network an opportunity to receive the corresponding source
agpl-3.0-only 60 1.0 [spdx] spdx licen[sc]e identifier agpl 3 0 only
agpl-3.0-or-later 60 1.0 [spdx] spdx licen[sc]e identifier agpl 3 0 or later
agpl-3.0 33 0.9 [affero] gnu affero general public licen[sc]e (?:version |v)?3(?: 0)?
agpl 47 0.95 [affero] (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?gnu affero general public licen[sc]e
agpl 14 0.6 [affero] gnu affero general public licen[sc]e
agpl 12 0.6 [agpl] (?:gnu )?agpl
agpl-3.0 31 0.85 [agplv3] (?:gnu )?agplv3
gfdl 75 1.0 [invariant] free documentation license version 1 [123] or any later version published by the free software foundation with no invariant sections
gfdl 70 0.9 [documentation] permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation license
gfdl-1.3 60 1.0 [spdx] spdx licen[sc]e identifier gfdl 1 3
gfdl 12 0.6 [documentation] gnu free documentation licen[sc]e
mpl-2.0 80 1.0 [mozilla] this source code form is subject to the terms of the mozilla public license v 2 0
mpl-2.0 78 0.9 [mpl] if a copy of the mpl was not distributed with this file you can obtain one at
mpl-1.1 80 1.0 [mozilla] the contents of this file are subject to the mozilla public license version 1 1
mpl-1.0 80 1.0 [mozilla] the contents of this file are subject to the mozilla public license version 1 0
mpl-2.0 60 1.0 [spdx] spdx licen[sc]e identifier mpl 2 0
mpl-2.0 30 0.9 [mozilla] mozilla public licen[sc]e (?:version |v ?)?2(?: 0)?
mpl-1.1 30 0.9 [mozilla] mozilla public licen[sc]e (?:version |v ?)?1 1
mpl 45 0.95 [mozilla] (?:licensed|released|distributed|available|published) under (?:the )?(?:terms of the )?mozilla public licen[sc]e
mpl 10 0.6 [mozilla] mozilla public licen[sc]e
npl-1.1 70 1.0 [netscape] the contents of this file are subject to the netscape public license
epl-2.0 80 1.0 [eclipse] made available under the terms of the eclipse public license (?:v |version )?2 0
epl-1.0 80 1.0 [eclipse] made available under the terms of the eclipse public license (?:v |version )?1 0
epl-2.0 60 1.0 [spdx] spdx licen[sc]e identifier epl 2 0
epl-1.0 60 1.0 [spdx] spdx licen[sc]e identifier epl 1 0
epl-2.0 30 0.9 [eclipse] eclipse public licen[sc]e (?:version |v ?)?2(?: 0)?
epl-1.0 30 0.9 [eclipse] eclipse public licen[sc]e (?:version |v ?)?1(?: 0)?
epl 10 0.6 [eclipse] eclipse public licen[sc]e
edl-1.0 30 0.9 [eclipse] eclipse distribution licen[sc]e (?:version |v ?)?1 0
cpl-1.0 30 0.9 [common public] common public licen[sc]e (?:version |v ?)?1 0
ipl-1.0 30 0.9 [public] ibm public licen[sc]e (?:version |v ?)?1 0
cddl-1.0 80 1.0 [common development] the contents of this file are subject to the terms of the common development and distribution license
cddl-1.0 60 1.0 [spdx] spdx licen[sc]e identifier cddl 1 0
cddl-1.1 60 1.0 [spdx] spdx licen[sc]e identifier cddl 1 1
cddl 12 0.6 [common development] common development and distribution licen[sc]e
eupl-1.2 80 1.0 [eupl] licensed under the eupl (?:version |v ?)?1 2
eupl-1.1 80 1.0 [eupl] licensed under the eupl (?:version |v ?)?1 1
eupl-1.2 60 1.0 [spdx] spdx licen[sc]e identifier eupl 1 2
eupl 12 0.6 [european union] european union public licen[sc]e
cecill-2.1 60 1.0 [spdx] spdx licen[sc]e identifier cecill 2 1
cecill 70 1.0 [cecill] this software is governed by the cecill(?: [bc])? license under french law
cecill-b 30 0.9 [cecill] cecill b licen[sc]e
cecill-c 30 0.9 [cecill] cecill c licen[sc]e
cecill 12 0.6 [cecill] cecill licen[sc]e
artistic-2.0 70 1.0 [artistic] everyone is permitted to copy and distribute verbatim copies of this license document(?: .{1,60}?)? artistic license
artistic-2.0 60 1.0 [spdx] spdx licen[sc]e identifier artistic 2 0
artistic-2.0 30 0.9 [artistic] artistic licen[sc]e (?:version |v)?2(?: 0)?
artistic-1.0 30 0.9 [artistic] artistic licen[sc]e (?:version |v)?1(?: 0)?
artistic 12 0.6 [artistic] (?:perl )?artistic licen[sc]e
perl 70 0.9 [perl] you can redistribute it and or modify it under the same terms as perl itself
zlib 70 1.0 [misrepresented] the origin of this software must not be misrepresented
zlib 70 0.9 [plainly] altered source versions must be plainly marked as such
zlib 66 0.8 [provided as is] this software is provided as is without any express or implied warranty in no event will the authors be held liable
zlib 60 1.0 [spdx] spdx licen[sc]e identifier zlib
zlib 12 0.6 [zlib] zlib (?:libpng )?licen[sc]e
libpng 70 0.9 [png] the png reference library is supplied as is
boost-1.0 75 1.0 [organization] permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation
boost-1.0 72 1.0 [boost] distributed under the boost software licen[sc]e(?: version 1 0)?
boost-1.0 60 1.0 [spdx] spdx licen[sc]e identifier bsl 1 0
boost-1.0 12 0.7 [boost] boost software licen[sc]e
busl-1.1 60 1.0 [spdx] spdx licen[sc]e identifier busl 1 1
busl-1.1 70 1.0 [business source] use of this software is governed by the business source license
busl-1.1 12 0.7 [business source] business source licen[sc]e
sspl-1.0 60 1.0 [spdx] spdx licen[sc]e identifier sspl 1 0
sspl-1.0 12 0.8 [server side] server side public licen[sc]e
elastic-2.0 60 1.0 [spdx] spdx licen[sc]e identifier elastic 2 0
elastic-2.0 12 0.8 [elastic] elastic licen[sc]e(?: 2 0)?
unlicense 80 1.0 [unencumbered] this is free and unencumbered software released into the public domain
unlicense 75 0.9 [compiled] anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary
unlicense 60 1.0 [spdx] spdx licen[sc]e identifier unlicense
unlicense 12 0.7 [unlicense] the unlicense
wtfpl 70 1.0 [the fuck] you just do what the fuck you want to
wtfpl 60 1.0 [spdx] spdx licen[sc]e identifier wtfpl
wtfpl 12 0.7 [wtfpl] (?:the )?wtfpl
python-2.0 70 1.0 [python] python software foundation license version 2
python-2.0 60 1.0 [spdx] spdx licen[sc]e identifier python 2 0
psf 12 0.6 [python] python software foundation licen[sc]e
psf 12 0.6 [psf] psf licen[sc]e
ruby 70 0.9 [ruby] distribute it under the same terms as ruby
php-3.01 70 1.0 [php] this source file is subject to version 3 01 of the php license
php 12 0.6 [php] php licen[sc]e
ofl-1.1 75 1.0 [font] this font software is licensed under the sil open font license version 1 1
ofl-1.1 70 0.9 [font] the font software may be sold as part of a larger software package but no copy of one or more of the font software typefaces may be sold by itself
ofl-1.1 60 1.0 [spdx] spdx licen[sc]e identifier ofl 1 1
ofl 12 0.6 [font] sil open font licen[sc]e
openssl 70 1.0 [openssl] this product includes software developed by the openssl project for use in the openssl toolkit
openssl 12 0.6 [openssl] openssl licen[sc]e
curl 60 1.0 [spdx] spdx licen[sc]e identifier curl
ms-pl 60 1.0 [spdx] spdx licen[sc]e identifier ms pl
ms-pl 12 0.7 [microsoft] microsoft public licen[sc]e
ms-rl 12 0.7 [microsoft] microsoft reciprocal licen[sc]e
beerware 70 1.0 [beer] you can buy me a beer in return
json 80 1.0 [evil] the software shall be used for good not evil
postgresql 60 1.0 [spdx] spdx licen[sc]e identifier postgresql
postgresql 12 0.7 [postgresql] postgresql licen[sc]e
upl-1.0 12 0.7 [permissive] universal permissive licen[sc]e
ncsa 30 0.9 [ncsa] university of illinois ncsa open source licen[sc]e
w3c 12 0.7 [w3c] w3c software (?:notice and )?licen[sc]e
unicode 70 0.9 [unicode] unicode licen[sc]e (?:agreement|v3)
odbl-1.0 12 0.8 [database] open database licen[sc]e
odc-by 12 0.8 [attribution] open data commons attribution licen[sc]e
pddl 12 0.8 [dedication] public domain dedication and licen[sc]e
cc0 75 1.0 [related] the person who associated a work with this deed has dedicated the work to the public domain by waiving all of his or her rights to the work worldwide under copyright law including all related and neighboring rights
cc0-1.0 60 1.0 [spdx] spdx licen[sc]e identifier cc0 1 0
cc0 30 0.9 [cc0] cc0(?: 1 0)?(?: universal)?
cc0 20 0.8 [zero] creative commons zero
cc-by-4.0 60 1.0 [spdx] spdx licen[sc]e identifier cc by 4 0
cc-by-sa-4.0 61 1.0 [spdx] spdx licen[sc]e identifier cc by sa 4 0
cc-by-nc-4.0 61 1.0 [spdx] spdx licen[sc]e identifier cc by nc 4 0
cc-by-nd-4.0 61 1.0 [spdx] spdx licen[sc]e identifier cc by nd 4 0
cc-by-nc-sa-4.0 62 1.0 [spdx] spdx licen[sc]e identifier cc by nc sa 4 0
cc-by 45 0.95 [creative] (?:licensed|released|distributed|available|published) under (?:the |a )?(?:terms of the )?creative commons attribution(?: [1-4] [05])?(?: international| unported)? licen[sc]e
cc-by-sa 46 0.95 [creative] (?:licensed|released|distributed|available|published) under (?:the |a )?(?:terms of the )?creative commons attribution share ?alike
cc-by-nc 46 0.95 [creative] (?:licensed|released|distributed|available|published) under (?:the |a )?(?:terms of the )?creative commons attribution non ?commercial
cc-by-nd 46 0.95 [creative] (?:licensed|released|distributed|available|published) under (?:the |a )?(?:terms of the )?creative commons attribution no ?deriv(?:ative)?s
cc-by-4.0 50 1.0 [creativecommons] creativecommons org licenses by 4 0
cc-by-3.0 50 1.0 [creativecommons] creativecommons org licenses by 3 0
cc-by-sa 51 1.0 [creativecommons] creativecommons org licenses by sa [1-4] [05]
cc-by-nc 51 1.0 [creativecommons] creativecommons org licenses by nc [1-4] [05]
cc-by-nd 51 1.0 [creativecommons] creativecommons org licenses by nd [1-4] [05]
cc-by-nc-sa 52 1.0 [creativecommons] creativecommons org licenses by nc sa [1-4] [05]
cc-by-nc-nd 52 1.0 [creativecommons] creativecommons org licenses by nc nd [1-4] [05]
cc0 51 1.0 [creativecommons] creativecommons org publicdomain zero 1 0
cc-by-4.0 30 0.9 [cc] cc by 4 0
cc-by-3.0 30 0.9 [cc] cc by 3 0
cc-by-sa 32 0.9 [cc] cc by sa(?: [1-4] [05])?
cc-by-nc-sa 34 0.9 [cc] cc by nc sa(?: [1-4] [05])?
cc-by-nc-nd 34 0.9 [cc] cc by nc nd(?: [1-4] [05])?
cc-by-nc 32 0.9 [cc] cc by nc(?: [1-4] [05])?
cc-by-nd 32 0.9 [cc] cc by nd(?: [1-4] [05])?
cc-by-sa 22 0.8 [creative] creative commons attribution share ?alike
cc-by-nc 22 0.8 [creative] creative commons attribution non ?commercial
cc-by-nd 22 0.8 [creative] creative commons attribution no ?deriv(?:ative)?s
cc-by 20 0.8 [creative] creative commons attribution
cc-by 10 0.6 [cc] cc by
public-domain 45 0.9 [public domain] (?:dedicated|released|placed|put) (?:to|in|into) the public domain
public-domain 40 0.7 [public domain] this (?:work|file|software|code|document|text) is in the public domain
proprietary 40 0.7 [confidential] (?:proprietary and confidential|confidential and proprietary)
proprietary 40 0.8 [strictly] unauthorized copying of this file via any medium is strictly prohibited
proprietary 8 0.4 [reserved] all rights reserved
"""
