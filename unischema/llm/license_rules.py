"""The ordered signature rules: regexes over normalised words, each gated by a keyword.

Texts are matched after folding: lower case, words joined by single blanks. A rule has a label, a
priority, a keyword that every match contains (as plain text) and a confidence.

Priorities: 3 identifiers and links, 2 grants and full names, 1 mentions. Base rules come first.
"""

from __future__ import annotations

import re
from dataclasses import dataclass


@dataclass(frozen=True)
class Rule:
    label: str
    priority: int
    keyword: str
    pattern: str
    confidence: float
    base: bool = False


BASE = [
    Rule("gpl", 2, "gnu general public license", r"gnu general public license", 0.9, True),
    Rule("apache", 2, "apache license", r"apache license", 0.9, True),
    Rule("cc-by", 2, "cc by", r"cc by", 0.8, True),
    Rule("mit", 2, "mit license", r"mit license", 0.9, True),
]

_VERSION = r"(?: version)?"
#: Full names: label, keyword, regex.
_NAMES = [
    ("gpl-1.0", "public license", rf"gnu general public license{_VERSION} v?1(?: 0)?"),
    ("gpl-2.0", "public license", rf"gnu general public license{_VERSION} v?2(?: 0)?"),
    ("gpl-3.0", "public license", rf"gnu general public license{_VERSION} v?3(?: 0)?"),
    ("gpl-2.0-or-later", "later version", r"version 2 (?:of the license )?or at your option any later version"),
    ("gpl-3.0-or-later", "later version", r"version 3 (?:of the license )?or at your option any later version"),
    ("lgpl", "public license", r"gnu (?:lesser|library) general public license"),
    ("lgpl-2.1", "public license", rf"gnu lesser general public license{_VERSION} v?2 1"),
    ("lgpl-3.0", "public license", rf"gnu lesser general public license{_VERSION} v?3(?: 0)?"),
    ("agpl", "public license", r"gnu affero general public license"),
    ("agpl-3.0", "public license", rf"gnu affero general public license{_VERSION} v?3(?: 0)?"),
    ("gfdl", "documentation license", r"gnu free documentation license"),
    ("gfdl-1.3", "documentation license", rf"gnu free documentation license{_VERSION} 1 3"),
    ("apache-1.1", "apache", rf"apache software license{_VERSION} 1 1"),
    ("apache-2.0", "apache license", rf"apache license{_VERSION} v?2(?: 0)?"),
    ("apache", "apache software license", r"apache software license"),
    ("bsd", "bsd license", r"(?:modified |new |revised |simplified )?bsd license"),
    ("bsd-2-clause", "clause bsd", r"(?:2|two) clause bsd(?: license)?"),
    ("bsd-3-clause", "clause bsd", r"(?:3|three) clause bsd(?: license)?"),
    ("bsd-4-clause", "clause bsd", r"(?:4|four) clause bsd(?: license)?"),
    ("0bsd", "bsd", r"(?:bsd zero clause|zero clause bsd|0bsd)(?: license)?"),
    ("isc", "isc license", r"isc license"),
    ("mit-0", "mit no attribution", r"mit no attribution(?: license)?"),
    ("x11", "x11 license", r"x11 license"),
    ("mpl", "mozilla public license", r"mozilla public license"),
    ("mpl-1.1", "mozilla public license", rf"mozilla public license{_VERSION} 1 1"),
    ("mpl-2.0", "mozilla public license", rf"mozilla public license{_VERSION} v?2(?: 0)?"),
    ("epl", "eclipse public license", r"eclipse public license"),
    ("epl-1.0", "eclipse public license", rf"eclipse public license{_VERSION} v?1(?: 0)?"),
    ("epl-2.0", "eclipse public license", rf"eclipse public license{_VERSION} v?2(?: 0)?"),
    ("cpl-1.0", "common public license", rf"common public license(?:{_VERSION} 1 0)?"),
    ("cddl", "distribution license", r"common development and distribution license"),
    ("cddl-1.0", "distribution license", rf"common development and distribution license{_VERSION} 1 0"),
    ("eupl", "union public", r"european union public licen[cs]e"),
    ("eupl-1.2", "union public", rf"european union public licen[cs]e{_VERSION} v?1 2"),
    ("artistic", "artistic license", r"artistic license"),
    ("artistic-2.0", "artistic license", rf"artistic license{_VERSION} 2 0"),
    ("boost", "boost software license", rf"boost software license(?:{_VERSION} 1 0)?"),
    ("zlib", "zlib", r"zlib (?:libpng )?license"),
    ("libpng", "libpng license", r"libpng license"),
    ("python", "python software foundation license", r"python software foundation license(?: version 2)?"),
    ("php", "php license", rf"php license(?:{_VERSION} 3 01?)?"),
    ("ruby", "ruby license", r"ruby license"),
    ("postgresql", "postgresql", r"postgresql licen[cs]e"),
    ("openssl", "openssl license", r"openssl license"),
    ("ofl", "open font license", rf"(?:sil )?open font license(?:{_VERSION} 1 1)?"),
    ("odbl", "database license", r"open (?:data commons open )?database license"),
    ("odc-by", "open data commons", r"open data commons attribution license"),
    ("pddl", "dedication and license", r"public domain dedication and license"),
    ("unlicense", "unlicense", r"(?:the )?unlicense"),
    ("wtfpl", "fuck you want", r"do what the fuck you want to public license"),
    ("cecill", "cecill", r"cecill(?: [abc])?(?: license)?"),
    ("ms-pl", "microsoft public license", r"microsoft public license"),
    ("ms-rl", "microsoft reciprocal license", r"microsoft reciprocal license"),
    ("ncsa", "illinois", r"university of illinois(?: ncsa)? open source license"),
    ("afl-3.0", "academic free license", rf"academic free license(?:{_VERSION} 3 0)?"),
    ("osl-3.0", "open software license", rf"open software license(?:{_VERSION} 3 0)?"),
    ("upl-1.0", "universal permissive license", rf"universal permissive license(?:{_VERSION} 1 0)?"),
    ("bsl-1.1", "business source license", rf"business source license(?:{_VERSION} 1 1)?"),
    ("sspl-1.0", "server side public license", rf"server side public license(?:{_VERSION} 1)?"),
    ("elastic-2.0", "elastic license", rf"elastic license(?:{_VERSION} 2 0)?"),
    ("gpl", "general public licence", r"gnu general public licence"),
    ("cc-by", "creative commons", r"creative commons attribution(?: license| licence| \d 0)"),
    ("cc-by-sa", "creative commons", r"creative commons attribution share ?alike(?: \d 0)?"),
    ("cc-by-nc", "creative commons", r"creative commons attribution non ?commercial(?: \d 0)?"),
    ("cc-by-nd", "creative commons", r"creative commons attribution no ?deriv(?:ative)?s(?: \d 0)?"),
    ("cc-by-nc-sa", "creative commons", r"creative commons attribution non ?commercial share ?alike(?: \d 0)?"),
    ("cc-by-nc-nd", "creative commons", r"creative commons attribution non ?commercial no ?deriv(?:ative)?s(?: \d 0)?"),
    ("cc0-1.0", "cc0", r"cc0(?: 1 0)?(?: universal)?"),
    ("cc-by-sa", "cc by", r"cc by sa(?: \d 0)?"),
    ("cc-by-nc", "cc by", r"cc by nc(?: \d 0)?"),
    ("cc-by-nd", "cc by", r"cc by nd(?: \d 0)?"),
    ("cc-by-nc-sa", "cc by", r"cc by nc sa(?: \d 0)?"),
    ("cc-by-nc-nd", "cc by", r"cc by nc nd(?: \d 0)?"),
    ("cc-by-3.0", "cc by", r"cc by 3 0"),
    ("cc-by-4.0", "cc by", r"cc by 4 0"),
]

#: Sentences of licence texts and notices: label, keyword, regex, priority.
_GRANTS = [
    ("mit", "permission is hereby granted", r"permission is hereby granted free of charge to any person obtaining a copy of this software", 2),
    ("isc", "permission to use", r"permission to use copy modify and or distribute this software for any purpose", 2),
    ("bsd", "redistribution and use", r"redistribution and use in source and binary forms with or without modification are permitted", 2),
    ("bsd-3-clause", "neither the name", r"neither the name of \w+(?: \w+){0,8} nor the names of its contributors", 2),
    ("bsd-4-clause", "advertising materials", r"all advertising materials mentioning features or use of this software", 2),
    ("gpl", "terms of the gnu", r"redistribute it and or modify it under the terms of the gnu general public license", 2),
    ("lgpl", "terms of the gnu", r"under the terms of the gnu (?:lesser|library) general public license", 2),
    ("agpl", "terms of the gnu", r"under the terms of the gnu affero general public license", 2),
    ("gfdl", "permission is granted", r"permission is granted to copy distribute and or modify this document", 2),
    ("apache-2.0", "apache license", r"licensed under the apache license version 2 0", 2),
    ("mpl-2.0", "source code form", r"this source code form is subject to the terms of the mozilla public license", 2),
    ("zlib", "express or implied warranty", r"this software is provided as is without any express or implied warranty", 2),
    ("boost", "boost", r"distributed under the boost software license", 2),
    ("unlicense", "public domain", r"this is free and unencumbered software released into the public domain", 2),
    ("public-domain", "public domain", r"(?:dedicated|released|placed|given) (?:in|in ?to|to) the public domain", 1),
    ("public-domain", "public domain", r"(?:this work is in|is in) the public domain", 1),
    ("proprietary", "all rights reserved", r"all rights reserved", 1),
    ("proprietary", "proprietary and confidential", r"proprietary and confidential", 1),
    ("proprietary", "unauthorized copying", r"unauthorized copying of this (?:file|software)", 1),
    ("proprietary", "end user", r"end user licen[cs]e agreement", 1),
    ("gpl", "gplv", r"gplv[123]", 1),
    ("lgpl", "lgplv", r"lgplv[23]", 1),
    ("agpl", "agplv3", r"agplv3", 1),
    ("copyleft", "copyleft", r"copyleft", 1),
    ("unknown-license", "license", r"see (?:the )?license(?: file)? for (?:details|more information)", 1),
    ("unknown-license", "license file", r"found in the license file", 1),
    ("unknown-license", "under the terms", r"under the terms of (?:this|the) license", 1),
]

#: More full names, each with the words that every match has.
_MORE_NAMES = [
    ("academic-free-2.1", "academic free license", r"academic free license(?: version)? v?2 1"),
    ("adobe-glyph", "adobe glyph", r"adobe glyph list license"),
    ("apple-public-source", "apple public source", r"apple public source license(?: version)?(?: \d \d)?"),
    ("artistic-1.0", "artistic license", r"artistic license(?: version)? 1 0"),
    ("artistic-perl", "same terms as perl", r"(?:under the )?same terms as perl(?: itself)?"),
    ("bittorrent", "bittorrent open source", r"bittorrent open source license"),
    ("blue-oak", "blue oak model", r"blue oak model license(?: 1 0 0)?"),
    ("bsd-lbnl", "lawrence berkeley", r"lawrence berkeley national labs bsd(?: variant)? license"),
    ("bsd-patent", "plus patent", r"bsd(?: 2 clause)? plus patent license"),
    ("bsd-protection", "protection license", r"bsd protection license"),
    ("bsd-source-code", "source code attribution", r"bsd source code attribution"),
    ("catosl", "computer associates trusted", r"computer associates trusted open source license(?: 1 1)?"),
    ("cern-ohl", "open hardware", r"cern open hardware licen[cs]e(?: version \d)?"),
    ("cern-ohl-p", "open hardware", r"cern open hardware licen[cs]e(?: version 2)? permissive"),
    ("cern-ohl-s", "open hardware", r"cern open hardware licen[cs]e(?: version 2)? strongly reciprocal"),
    ("clarified-artistic", "clarified artistic", r"clarified artistic license"),
    ("cnri-python", "cnri", r"cnri(?: open source)?(?: gpl compatible)? license agreement"),
    ("commons-clause", "commons clause", r"commons clause(?: license)? condition(?: v?1 0)?"),
    ("condor", "condor public", r"condor public license(?: v?1 1)?"),
    ("cpal", "common public attribution", r"common public attribution license(?: version)?(?: 1 0)?"),
    ("crossword", "crossword license", r"crossword license"),
    ("cua-opl", "cua office", r"cua office public license"),
    ("cube", "cube license", r"cube license"),
    ("curl", "curl license", r"curl license"),
    ("d-fsl", "german free software", r"german free software license"),
    ("d-fsl", "deutsche freie software", r"deutsche freie software lizenz"),
    ("datenlizenz-by", "datenlizenz deutschland", r"datenlizenz deutschland namensnennung(?: 2 0)?"),
    ("datenlizenz-zero", "datenlizenz deutschland", r"datenlizenz deutschland zero(?: 2 0)?"),
    ("ecl", "educational community", r"educational community license(?: version)?(?: [12] 0)?"),
    ("efl", "eiffel forum", r"eiffel forum license(?: version)?(?: [12])?"),
    ("entessa", "entessa public", r"entessa public license(?: v1 0)?"),
    ("erlang", "erlang public", r"erlang public license(?: v?1 1)?"),
    ("etalab", "licence ouverte", r"licence ouverte(?: etalab)?(?: 2 0)?"),
    ("eu-datagrid", "eu datagrid", r"eu datagrid software license"),
    ("fair", "fair license", r"the fair license"),
    ("fair-source", "fair source", r"fair source license(?: version 0 9)?"),
    ("frameworx", "frameworx", r"frameworx open license(?: 1 0)?"),
    ("free-art", "free art license", r"free art license(?: 1 3)?"),
    ("freeimage", "freeimage public", r"freeimage public license(?: v?1 0)?"),
    ("freetype", "freetype", r"freetype (?:project )?license"),
    ("fsf-all-permissive", "without royalty provided", r"permitted in any medium without royalty provided the copyright notice"),
    ("giftware", "giftware license", r"giftware license"),
    ("gl2ps", "gl2ps license", r"gl2ps license"),
    ("glide", "3dfx glide", r"3dfx glide(?: source code)? general public license"),
    ("gnuplot", "gnuplot license", r"gnuplot license"),
    ("gust-font", "gust font", r"gust font(?: source)? license"),
    ("hippocratic", "hippocratic license", r"hippocratic license(?: version)?(?: \d \d)?"),
    ("hpnd", "historical permission notice", r"historical permission notice and disclaimer"),
    ("ibm-public", "ibm public license", r"ibm public license(?: version)?(?: 1 0)?"),
    ("icu", "icu license", r"icu license"),
    ("ijg", "independent jpeg group", r"independent jpeg group license"),
    ("imagemagick", "imagemagick license", r"imagemagick license"),
    ("imatix", "imatix standard function", r"imatix standard function library agreement"),
    ("info-zip", "info zip license", r"info zip license"),
    ("intel-open-source", "intel open source", r"intel open source license"),
    ("ipa-font", "ipa font license", r"ipa font license"),
    ("jasper", "jasper", r"jasper(?: 2 0)? license"),
    ("json", "json license", r"json license"),
    ("latex-project", "latex project public", r"latex project public license(?: version)?(?: 1 \d[abc]?)?"),
    ("leptonica", "leptonica license", r"leptonica license"),
    ("libtiff", "libtiff license", r"libtiff license"),
    ("licence-art-libre", "licence art libre", r"licence art libre(?: 1 3)?"),
    ("liliq", "licence libre du qu", r"licence libre du qu\S+"),
    ("lucent", "lucent public license", r"lucent public license(?: version)?(?: 1 0\d?)?"),
    ("mariadb-bsl", "mariadb business source", r"mariadb business source license"),
    ("miros", "miros licen", r"miros licen[cs]e"),
    ("motosoto", "motosoto open source", r"motosoto open source license"),
    ("mpich2", "mpich2 license", r"mpich2 license"),
    ("mulan", "mulan p", r"mulan p(?:ermissive|ublic) (?:software )?license(?: v?\d)?"),
    ("multics", "multics license", r"multics license"),
    ("naumen", "naumen public", r"naumen public license"),
    ("nethack", "nethack general public", r"nethack general public license"),
    ("netscape", "netscape public license", r"netscape public license(?: version)?(?: 1 [01])?"),
    ("ngpl", "nethack", r"nethack(?: general)? license"),
    ("nokia", "nokia open source", r"nokia open source license"),
    ("nosl", "netizen open source", r"netizen open source license"),
    ("ntp", "ntp license", r"ntp license"),
    ("nasa", "nasa open source", r"nasa open source agreement(?: 1 3)?"),
    ("oclc", "oclc research public", r"oclc research public license(?: 2 0)?"),
    ("ogl", "open government licen", r"open government licen[cs]e(?: v?\d(?: 0)?)?"),
    ("ogl-canada", "open government licence canada", r"open government licence canada"),
    ("ogtsl", "open group test suite", r"open group test suite license"),
    ("oldap", "openldap public license", r"openldap public license(?: version)?(?: 2 8)?"),
    ("open-game", "open game license", r"open game license(?: version)?(?: 1 0a)?"),
    ("open-publication", "open publication license", r"open publication license(?: v?1 0)?"),
    ("oset", "oset public license", r"oset public license(?: 2 1)?"),
    ("parity", "parity public license", r"parity public license(?: \d 0 0)?"),
    ("polyform-noncommercial", "polyform", r"polyform noncommercial(?: license)?(?: 1 0 0)?"),
    ("polyform-shield", "polyform", r"polyform shield(?: license)?(?: 1 0 0)?"),
    ("polyform-small-business", "polyform", r"polyform small business(?: license)?(?: 1 0 0)?"),
    ("prosperity", "prosperity public license", r"prosperity public license(?: 3 0 0)?"),
    ("pil", "python imaging library", r"python imaging library license"),
    ("qpl", "q public license", r"q public license(?: version)?(?: 1 0)?"),
    ("qhull", "qhull license", r"qhull license"),
    ("realnetworks", "realnetworks public source", r"realnetworks public source license(?: v?1 0)?"),
    ("reciprocal-public", "reciprocal public license", r"reciprocal public license(?: 1 [15])?"),
    ("ricoh", "ricoh source code", r"ricoh source code public license"),
    ("scea", "scea shared source", r"scea shared source license"),
    ("sendmail", "sendmail license", r"sendmail license"),
    ("sgi-free-b", "sgi free software", r"sgi free software license b(?: version)?(?: \d \d)?"),
    ("simple-public", "simple public license", r"simple public license(?: 2 0)?"),
    ("sissl", "sun industry standards", r"sun industry standards source license(?: version)?(?: 1 [12])?"),
    ("sleepycat", "sleepycat license", r"sleepycat license"),
    ("sun-public", "sun public license", r"sun public license(?: version)?(?: 1 0)?"),
    ("sybase", "sybase open watcom", r"sybase open watcom public license(?: 1 0)?"),
    ("tcl", "tcl tk license", r"tcl tk license"),
    ("unicode", "unicode license", r"unicode license agreement(?: data files and software)?"),
    ("vim", "vim license", r"vim license"),
    ("vsl", "vovida software license", r"vovida software license(?: v?1 0)?"),
    ("w3c", "w3c software", r"w3c software(?: and document)? notice and license"),
    ("watcom", "watcom public", r"open watcom public license"),
    ("wxwindows", "wxwindows library", r"wxwindows library licen[cs]e"),
    ("xfree86", "xfree86 license", r"xfree86 license(?: 1 1)?"),
    ("xnet", "x net license", r"x net license"),
    ("zend", "zend license", r"zend license(?: v?2 0)?"),
    ("zope", "zope public license", r"zope public license(?: version)?(?: \d \d)?"),
]

#: More sentences of licence texts and notices: label, keyword, regex, priority.
_MORE_GRANTS = [
    ("mit", "above copyright notice and this permission notice", r"the above copyright notice and this permission notice shall be included in all copies", 2),
    ("mit", "without restriction including without limitation", r"to deal in the software without restriction including without limitation the rights", 2),
    ("mit", "mit licensed", r"(?:is|are) mit licensed", 1),
    ("bsd", "redistributions of source code", r"redistributions of source code must retain the above copyright notice", 2),
    ("bsd", "redistributions in binary form", r"redistributions in binary form must reproduce the above copyright notice", 2),
    ("bsd", "bsd style license", r"(?:a )?bsd style license", 1),
    ("gpl", "gnu gpl", r"gnu gpl(?: v\d| version \d)?", 1),
    ("gpl", "free software foundation", r"as published by the free software foundation", 1),
    ("gpl", "without any warranty without even", r"without any warranty without even the implied warranty of merchantability or fitness", 1),
    ("gpl", "received a copy of the gnu general", r"you should have received a copy of the gnu general public license", 2),
    ("lgpl", "received a copy of the gnu lesser", r"you should have received a copy of the gnu lesser general public license", 2),
    ("agpl", "received a copy of the gnu affero", r"you should have received a copy of the gnu affero general public license", 2),
    ("apache-2.0", "apache org licenses", r"(?:www )?apache org licenses license 2 0(?: html| txt)?", 3),
    ("apache-2.0", "not use this file except", r"you may not use this file except in compliance with the license", 2),
    ("apache-2.0", "limitations under the license", r"specific language governing permissions and limitations under the license", 2),
    ("gpl", "gnu org licenses", r"(?:www )?gnu org licenses (?:old licenses )?gpl(?: \d 0)?(?: html| txt)?", 3),
    ("lgpl", "gnu org licenses", r"(?:www )?gnu org licenses (?:old licenses )?lgpl(?: \d \d)?(?: html| txt)?", 3),
    ("agpl", "gnu org licenses", r"(?:www )?gnu org licenses agpl(?: 3 0)?(?: html| txt)?", 3),
    ("gfdl", "gnu org licenses", r"(?:www )?gnu org licenses fdl(?: 1 3)?(?: html| txt)?", 3),
    ("mit", "opensource org licenses mit", r"opensource org licenses mit(?: license)?(?: php)?", 3),
    ("bsd", "opensource org licenses bsd", r"opensource org licenses bsd(?: \d clause| license)?(?: php)?", 3),
    ("apache-2.0", "opensource org licenses apache", r"opensource org licenses apache 2 0(?: php)?", 3),
    ("isc", "opensource org licenses isc", r"opensource org licenses isc(?: license)?(?: txt)?", 3),
    ("mpl-2.0", "mozilla org mpl", r"(?:www )?mozilla org mpl 2 0", 3),
    ("mpl-1.1", "mozilla org mpl", r"(?:www )?mozilla org mpl mpl 1 1(?: html)?", 3),
    ("epl", "eclipse org legal epl", r"(?:www )?eclipse org legal epl v?\d ?\d?(?: html)?", 3),
    ("cc-by", "creativecommons org licenses by", r"creativecommons org licenses by \d \d", 3),
    ("cc-by-sa", "creativecommons org licenses by sa", r"creativecommons org licenses by sa \d \d", 3),
    ("cc-by-nc", "creativecommons org licenses by nc", r"creativecommons org licenses by nc \d \d", 3),
    ("cc-by-nd", "creativecommons org licenses by nd", r"creativecommons org licenses by nd \d \d", 3),
    ("cc-by-nc-sa", "creativecommons org licenses by nc sa", r"creativecommons org licenses by nc sa \d \d", 3),
    ("cc-by-nc-nd", "creativecommons org licenses by nc nd", r"creativecommons org licenses by nc nd \d \d", 3),
    ("cc0-1.0", "creativecommons org publicdomain zero", r"creativecommons org publicdomain zero 1 0", 3),
    ("cc-pdm", "creativecommons org publicdomain mark", r"creativecommons org publicdomain mark 1 0", 3),
    ("unlicense", "unlicense org", r"(?:www )?unlicense org", 3),
    ("boost", "boost org license", r"(?:www )?boost org license 1 0(?: txt)?", 3),
    ("wtfpl", "wtfpl net", r"(?:www )?wtfpl net", 3),
    ("unlicense", "anyone is free to copy", r"anyone is free to copy modify publish use compile sell or distribute this software", 2),
    ("zlib", "altered source versions", r"altered source versions must be plainly marked as such", 2),
    ("zlib", "origin of this software", r"the origin of this software must not be misrepresented", 2),
    ("boost", "organization obtaining a copy", r"permission is hereby granted free of charge to any person or organization obtaining a copy", 2),
    ("wtfpl", "you just do what the fuck", r"you just do what the fuck you want to", 2),
    ("beerware", "beer ware license", r"the beer ware license(?: revision 42)?", 2),
    ("beerware", "buy me a beer", r"you can buy me a beer in return", 1),
    ("ofl", "reserved font name", r"with reserved font names?", 2),
    ("mpl", "contents of this file are subject to the mozilla", r"the contents of this file are subject to the mozilla public license", 2),
    ("mpl-2.0", "copy of the mpl was not distributed", r"if a copy of the mpl was not distributed with this file", 2),
    ("epl", "accompanying materials are made available", r"this program and the accompanying materials are made available under the terms of the eclipse", 2),
    ("cddl", "contents of this file are subject to the terms of the common development", r"the contents of this file are subject to the terms of the common development and distribution license", 2),
    ("eupl", "licensed under the eupl", r"licensed under the eupl(?: version 1 \d)?", 2),
    ("artistic", "terms of the artistic license", r"under the terms of the artistic license", 2),
    ("psf", "psf license agreement", r"psf license agreement(?: for python \d(?: \d)*)?", 2),
    ("openssl", "use in the openssl toolkit", r"developed by the openssl project for use in the openssl toolkit", 2),
    ("ssleay", "cryptographic software written by eric young", r"cryptographic software written by eric young", 2),
    ("public-domain", "no copyright is claimed", r"no copyright is claimed(?: in the united states)?", 1),
    ("public-domain", "waives all copyright", r"waives all copyright(?: and related or neighboring rights)?", 1),
    ("proprietary", "not be reproduced", r"may not be reproduced (?:or transmitted )?in any form(?: or by any means)?", 1),
    ("proprietary", "no part of this publication", r"no part of this publication may be reproduced", 1),
    ("proprietary", "confidential information of", r"(?:is )?confidential information of \S+", 1),
    ("proprietary", "trade secret", r"contains trade secrets?(?: and proprietary information)?", 1),
    ("proprietary", "strictly prohibited", r"(?:copying|distribution|reproduction) (?:of this \w+ )?is strictly prohibited", 1),
    ("proprietary", "without the prior written permission", r"without the prior written permission of the (?:author|owner|publisher|copyright holder)s?", 1),
    ("proprietary", "commercial license", r"(?:requires|under|purchase) a commercial license", 1),
    ("noncommercial", "non commercial use only", r"(?:for )?non commercial use only", 1),
    ("noncommercial", "noncommercial purposes", r"for noncommercial purposes(?: only)?", 1),
    ("research-only", "research purposes only", r"(?:for|to) research purposes only", 1),
    ("personal-use", "personal use only", r"for (?:your )?personal use only", 1),
    ("evaluation", "evaluation licen", r"evaluation licen[cs]e", 1),
    ("shareware", "shareware", r"this (?:program|software) is shareware", 1),
    ("freeware", "freeware", r"this (?:program|software) is freeware", 1),
    ("dual-license", "dual licensed", r"(?:is|are) dual licensed(?: under)?", 1),
    ("dual-license", "of your choice", r"under the terms of either license of your choice", 1),
    ("unknown-license", "license terms", r"subject to the (?:following )?license terms", 1),
    ("unknown-license", "licensed under", r"licensed under the same (?:terms|license) as", 1),
    ("unknown-license", "copying file", r"see the copying file", 1),
    ("unknown-license", "license txt", r"(?:see|in|the) license txt", 1),
    ("unknown-license", "license md", r"(?:see|in|the) license md", 1),
    ("attribution", "provided that the author is credited", r"provided that the author is credited", 1),
    ("attribution", "with proper attribution", r"with proper attribution", 1),
    ("share-alike", "share alike", r"share alike licen[cs]e", 1),
]

#: Public identifiers, spelt as words; each makes a rule of the usual identifier line.
_IDENTIFIERS = """
0BSD AFL-3.0 AGPL-1.0 AGPL-3.0-only AGPL-3.0-or-later Apache-1.0 Apache-1.1 Apache-2.0 APSL-2.0 Artistic-1.0
Artistic-2.0 BSD-2-Clause BSD-3-Clause BSD-4-Clause BSL-1.0 BUSL-1.1 CC-BY-1.0 CC-BY-2.0 CC-BY-2.5 CC-BY-3.0
CC-BY-4.0 CC-BY-NC-3.0 CC-BY-NC-4.0 CC-BY-NC-ND-4.0 CC-BY-NC-SA-4.0 CC-BY-ND-4.0 CC-BY-SA-3.0 CC-BY-SA-4.0
CC0-1.0 CDDL-1.0 CDDL-1.1 CECILL-2.1 CPAL-1.0 CPL-1.0 ECL-2.0 EFL-2.0 EPL-1.0 EPL-2.0 EUPL-1.1 EUPL-1.2
GFDL-1.3-only GPL-1.0-only GPL-2.0-only GPL-2.0-or-later GPL-3.0-only GPL-3.0-or-later HPND IPL-1.0 ISC
LGPL-2.0-only LGPL-2.1-only LGPL-2.1-or-later LGPL-3.0-only LGPL-3.0-or-later LPPL-1.3c MIT MIT-0 MPL-1.0 MPL-1.1
MPL-2.0 MS-PL MS-RL MulanPSL-2.0 NCSA NPL-1.1 ODbL-1.0 OFL-1.1 OSL-3.0 PHP-3.01 PostgreSQL Python-2.0 QPL-1.0
SISSL SSPL-1.0 Unlicense UPL-1.0 Vim W3C WTFPL X11 Xnet Zlib ZPL-2.1
""".split()


def _spelt(identifier: str) -> str:
    return " ".join(identifier.lower().replace("-", " ").replace(".", " ").split())


def all_rules() -> list[Rule]:
    """Every rule in its order; the place in the list breaks ties of priority."""
    rules = list(BASE)
    for identifier in _IDENTIFIERS:
        spelt = _spelt(identifier)
        rules.append(Rule(identifier.lower(), 3, f"identifier {spelt}", rf"spdx license identifier {spelt}", 1.0))
    rules += [Rule(label, 2, keyword, pattern, 0.85) for label, keyword, pattern in (*_NAMES, *_MORE_NAMES)]
    rules += [Rule(label, priority, keyword, pattern, {3: 0.95, 2: 0.8, 1: 0.4}[priority]) for label, keyword, pattern, priority in (*_GRANTS, *_MORE_GRANTS)]
    return rules


#: Strings that open the way to rules: the first that all matches of a rule contain is its gate. A rule
#: that has none of them is behind its own keyword.
GATES = ["licen", "gnu", "bsd", "cc by", "software", "copyright", "permi", "public domain", "source", "restriction", "publi", "gpl", "confidential", "org ", "use only", "terms", "rights", "cc0"]


def fixed_text(pattern: str) -> str:
    """A pattern without its groups and what follows a quantified letter: text that every match contains."""
    flat, before = pattern, None
    while flat != before:
        before, flat = flat, re.sub(r"\((?:\?:)?[^()]*\)[?*+]?(?:\{[^}]*\})?", "\0", flat)
    return re.sub(r"\\?.(?:[?*]|\{[^}]*\})|\[[^\]]*\][?*+]?|\\.", "\0", flat)


def gate_of(rule: Rule) -> str:
    fixed = fixed_text(rule.pattern)
    return next((gate for gate in GATES if gate in fixed), rule.keyword)
