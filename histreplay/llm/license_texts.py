"""Sentences of public licence texts and notices, as patterns over single-spaced lower-case words: label, keyword, pattern."""

#: Fixed values, one signature a line. Every match of a pattern holds its keyword.
SENTENCES = (
    # MIT and its relatives
    ("mit", "permission is hereby granted", r"permission is hereby granted free of charge to any person obtaining a copy of this software"),
    ("mit", "without restriction", r"to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense"),
    ("mit", "permission notice", r"the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software"),
    ("mit", "merchantability", r"the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability"),
    ("mit", "copyright holders be liable", r"in no event shall the authors or copyright holders be liable for any claim damages or other liability"),
    ("mit-0", "mit no attribution", r"mit no attribution"),
    ("mit", "mit style", r"mit style licen[sc]e"),
    ("x11", "x consortium", r"except as contained in this notice the name of the x consortium shall not be used"),
    ("x11", "mit x11", r"mit x11 licen[sc]e"),
    ("ntp", "suitability of this software", r"makes no representations about the suitability of this software for any purpose"),
    ("hpnd", "supporting documentation", r"that both (?:that|the above) copyright notice and this permission notice appear in supporting documentation"),
    ("isc", "permission to use copy modify", r"permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    ("isc", "author disclaims all warranties", r"the software is provided as is and the author disclaims all warranties with regard to this software"),
    ("boost", "permission is hereby granted", r"permission is hereby granted free of charge to any person or organization obtaining a copy of the software"),
    ("boost", "machine executable object code", r"machine executable object code generated by a source language processor"),
    ("ncsa", "illinois ncsa", r"university of illinois ncsa open source licen[sc]e"),
    ("curl", "copyright holder shall not be used", r"the name of a copyright holder shall not be used in advertising or otherwise to promote the sale"),
    ("json", "used for good not evil", r"the software shall be used for good not evil"),
    # BSD
    ("bsd", "redistribution and use", r"redistribution and use in source and binary forms with or without modification are permitted"),
    ("bsd", "redistributions of source code", r"redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer"),
    ("bsd", "redistributions in binary form", r"redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer"),
    ("bsd", "and contributors as is", r"this software is provided by the (?:copyright holders|regents) and contributors as is"),
    ("bsd", "substitute goods", r"procurement of substitute goods or services loss of use data or profits or business interruption"),
    ("bsd-3-clause", "names of its contributors", r"neither the name of .{1,80}? nor the names of its contributors may be used to endorse or promote"),
    ("bsd-3-clause", "used to endorse or promote products", r"the name of the author may not be used to endorse or promote products derived from this software"),
    ("bsd-4-clause", "advertising materials", r"all advertising materials mentioning features or use of this software"),
    ("bsd-3-clause", "bsd style", r"(?:3|three) clause bsd style licen[sc]e"),
    ("bsd", "bsd style", r"bsd style licen[sc]e"),
    ("bsd-2-clause", "views and conclusions", r"the views and conclusions contained in the software and documentation are those of the authors"),
    ("bsd-3-clause-clear", "clear bsd", r"(?:the )?clear bsd licen[sc]e"),
    ("0bsd", "zero clause bsd", r"zero clause bsd"),
    # GNU
    ("gpl", "under the terms of the gnu general public", r"you can redistribute it and or modify it under the terms of the gnu general public licen[sc]e"),
    ("lgpl", "under the terms of the gnu lesser general public", r"you can redistribute it and or modify it under the terms of the gnu lesser general public licen[sc]e"),
    ("lgpl", "under the terms of the gnu library general public", r"you can redistribute it and or modify it under the terms of the gnu library general public licen[sc]e"),
    ("agpl", "under the terms of the gnu affero general public", r"you can redistribute it and or modify it under the terms of the gnu affero general public licen[sc]e"),
    ("gpl", "you should have received a copy of the gnu general public", r"you should have received a copy of the gnu general public licen[sc]e along with"),
    ("lgpl", "you should have received a copy of the gnu lesser general public", r"you should have received a copy of the gnu lesser general public licen[sc]e along with"),
    ("agpl", "you should have received a copy of the gnu affero general public", r"you should have received a copy of the gnu affero general public licen[sc]e along with"),
    ("gpl", "gnu org licenses gpl", r"gnu org licenses gpl"),
    ("lgpl", "gnu org licenses lgpl", r"gnu org licenses lgpl"),
    ("agpl", "gnu org licenses agpl", r"gnu org licenses agpl"),
    ("gfdl", "gnu org licenses fdl", r"gnu org licenses fdl"),
    ("gfdl", "invariant sections", r"with no invariant sections no front cover texts and no back cover texts"),
    ("gpl-linking-exception", "linking this", r"linking this (?:library|program) statically or dynamically with other modules is making a combined work"),
    ("gpl-classpath-exception", "classpath exception", r"classpath exception"),
    ("gcc-exception", "gcc runtime library exception", r"gcc runtime library exception"),
    ("gpl", "free software foundation either version", r"as published by the free software foundation either version"),
    ("gpl", "general public licen", r"the licen[sc]es for most software are designed to take away your freedom to share and change it by contrast the gnu general public licen[sc]e"),
    ("agpl", "remote network interaction", r"remote network interaction use with the gnu general public licen[sc]e"),
    # Apache, Mozilla, Eclipse and other named families
    ("apache-2.0", "you may not use this file except", r"you may not use this file except in compliance with the licen[sc]e"),
    ("apache-2.0", "apache org licenses license 2 0", r"apache org licenses license 2 0"),
    ("apache-2.0", "agreed to in writing", r"unless required by applicable law or agreed to in writing software distributed under the licen[sc]e is distributed on an as is basis"),
    ("apache-2.0", "apache software foundation", r"licensed to the apache software foundation asf under one or more contributor"),
    ("apache-2.0", "patent license", r"perpetual worldwide non exclusive no charge royalty free irrevocable (?:except as stated in this section )?patent license"),
    ("apache-1.1", "developed by the apache software foundation", r"this product includes software developed by the apache software foundation"),
    ("mpl-2.0", "mozilla org mpl", r"mozilla org mpl 2 0"),
    ("mpl-1.1", "mozilla org mpl", r"mozilla org mpl mpl 1 1"),
    ("mpl-2.0", "source code form is subject", r"this source code form is subject to the terms of the mozilla public licen[sc]e"),
    ("mpl", "contents of this file are subject to the mozilla public", r"the contents of this file are subject to the mozilla public licen[sc]e"),
    ("mpl-2.0", "incompatible with secondary", r"this source code form is incompatible with secondary licen[sc]es"),
    ("epl", "eclipse org legal epl", r"eclipse org legal epl"),
    ("epl", "accompanying materials", r"this program and the accompanying materials are made available under the terms of the eclipse public licen[sc]e"),
    ("cpl", "common public licen", r"common public licen[sc]e"),
    ("ipl", "ibm public licen", r"ibm public licen[sc]e"),
    ("cddl", "contents of this file are subject to the terms of the common development", r"the contents of this file are subject to the terms of the common development and distribution licen[sc]e"),
    ("eupl", "joinup ec europa eu", r"joinup ec europa eu"),
    ("cecill", "cecill info", r"(?:www )?cecill info"),
    ("artistic", "standard version of", r"you may make and give away verbatim copies of the source form of the standard version of (?:this|the) package"),
    ("perl", "same terms as perl", r"under the same terms as perl(?: itself)?"),
    ("ruby", "same terms as ruby", r"under the same terms as ruby(?: itself)?"),
    ("ruby", "ruby licen", r"ruby licen[sc]e"),
    ("python", "psf licen", r"psf licen[sc]e"),
    ("python", "python software foundation licen", r"python software foundation licen[sc]e agreement"),
    ("php", "php net license", r"php net license"),
    ("tcl", "tcl tk licen", r"tcl tk licen[sc]e"),
    ("vim", "vim licen", r"vim licen[sc]e"),
    ("postgresql", "postgresql licen", r"postgresql licen[sc]e"),
    ("openssl", "openssl licen", r"openssl licen[sc]e"),
    ("openssl", "openssl toolkit", r"software developed by the openssl project for use in the openssl toolkit"),
    ("ssleay", "cryptographic software written by eric young", r"this product includes cryptographic software written by eric young"),
    ("openldap", "openldap public licen", r"openldap public licen[sc]e"),
    ("ofl-1.1", "sil open font", r"sil open font licen[sc]e(?:,? version)? 1 1"),
    ("ofl", "sil open font", r"sil open font licen[sc]e"),
    ("ofl", "reserved font name", r"with reserved font name"),
    ("ufl", "ubuntu font", r"ubuntu font licen[sc]e"),
    ("libpng", "libpng licen", r"libpng licen[sc]e"),
    ("zlib", "this software is provided", r"this software is provided as is without any express or implied warranty in no event will the authors be held liable"),
    ("zlib", "altered source versions", r"altered source versions must be plainly marked as such and must not be misrepresented"),
    ("zlib", "origin of this software", r"the origin of this software must not be misrepresented you must not claim that you wrote the original software"),
    ("ijg", "independent jpeg group", r"this software is based in part on the work of the independent jpeg group"),
    ("unicode", "unicode licen", r"unicode licen[sc]e(?: agreement)?"),
    ("icu", "icu licen", r"icu licen[sc]e"),
    ("w3c", "w3c software", r"w3c software (?:notice )?and (?:document )?licen[sc]e"),
    ("w3c", "w3c software licen", r"w3c software licen[sc]e"),
    ("mulan-psl", "mulan permissive", r"mulan permissive software licen[sc]e"),
    ("blueoak", "blue oak model", r"blue oak model licen[sc]e"),
    ("qpl", "q public licen", r"q public licen[sc]e"),
    ("sleepycat", "sleepycat", r"sleepycat (?:software|licen[sc]e)"),
    ("watcom", "sybase open watcom", r"sybase open watcom public licen[sc]e"),
    ("apsl", "apple public source", r"apple public source licen[sc]e"),
    ("nposl", "non profit open software", r"non profit open software licen[sc]e"),
    ("rpl", "reciprocal public licen", r"reciprocal public licen[sc]e"),
    ("sspl", "server side public", r"server side public licen[sc]e"),
    ("elastic", "elastic licen", r"elastic licen[sc]e"),
    ("busl", "business source licen", r"business source licen[sc]e"),
    ("commons-clause", "commons clause", r"commons clause licen[sc]e condition"),
    ("polyform", "polyform", r"polyform (?:noncommercial|small business|shield|strict|perimeter) licen[sc]e"),
    ("hippocratic", "hippocratic licen", r"hippocratic licen[sc]e"),
    ("parity", "parity public licen", r"parity public licen[sc]e"),
    ("rail", "open rail", r"(?:creativeml )?open rail(?: m| d| s)? licen[sc]e"),
    ("rail", "responsible ai licen", r"responsible ai licen[sc]e"),
    # Dedications
    ("public-domain", "public domain", r"(?:released|placed|dedicated) (?:in|into|to) the public domain"),
    ("public-domain", "in the public domain", r"this (?:file|work|code|software|program) is in the public domain"),
    ("public-domain", "public domain", r"public domain work of the (?:us|united states) government"),
    ("public-domain", "no known copyright", r"no known copyright restrictions"),
    ("unlicense", "unencumbered", r"this is free and unencumbered software released into the public domain"),
    ("unlicense", "unlicense org", r"unlicense org"),
    ("cc0", "cc0", r"cc0(?: 1 0(?: universal)?)?"),
    ("cc0", "creativecommons org publicdomain", r"creativecommons org publicdomain zero 1 0"),
    ("cc0", "dedicated the work to the public domain", r"has dedicated the work to the public domain by waiving all"),
    ("pddl", "public domain dedication and licen", r"public domain dedication and licen[sc]e"),
    ("odc-by", "open data commons attribution", r"open data commons attribution licen[sc]e"),
    ("odbl", "open data commons open database", r"open data commons open database licen[sc]e"),
    ("ogl", "open government licen", r"open government licen[sc]e"),
    ("ogl", "crown copyright", r"crown copyright"),
    ("ogl", "contains public sector information", r"contains public sector information"),
    ("etalab", "licence ouverte", r"licence ouverte"),
    ("dl-de", "datenlizenz deutschland", r"datenlizenz deutschland(?: namensnennung| zero)?"),
    ("cdla", "community data license", r"community data license agreement (?:permissive|sharing)"),
    ("wtfpl", "want to public", r"do what the (?:fuck|hell) you want to public licen[sc]e"),
    ("beerware", "beer", r"beer ?ware licen[sc]e"),
    ("beerware", "buy me a beer", r"you can buy me a beer in return"),
    # Content
    ("cc-by-sa", "wikipedia", r"text is available under the creative commons attribution share ?alike licen[sc]e.{0,60}?wikipedia"),
    ("cc", "creativecommons org licenses", r"creativecommons org licenses"),
    ("cc", "some rights reserved", r"some rights reserved"),
    ("gutenberg", "project gutenberg licen", r"project gutenberg licen[sc]e"),
    ("open-game", "open game licen", r"open game licen[sc]e"),
    ("free-art", "free art licen", r"free art licen[sc]e"),
    ("ietf", "ietf trust", r"ietf trust and the persons identified as the document authors"),
    # Closed
    ("proprietary", "all rights reserved", r"all rights reserved"),
    ("proprietary", "alle rechte vorbehalten", r"alle rechte vorbehalten"),
    ("proprietary", "tous droits réservés", r"tous droits réservés"),
    ("proprietary", "todos los derechos reservados", r"todos los derechos reservados"),
    ("proprietary", "proprietary and confidential", r"proprietary and confidential"),
    ("proprietary", "confidential and proprietary", r"confidential and proprietary"),
    ("proprietary", "trade secret", r"(?:contains|constitutes|are) (?:the )?(?:valuable )?trade secrets? of"),
    ("proprietary", "unauthorized copying", r"unauthorized copying of this file via any medium is strictly prohibited"),
    ("proprietary", "strictly prohibited", r"(?:reproduction|redistribution|copying|duplication) (?:in whole or in part )?(?:without permission )?is strictly prohibited"),
    ("eula", "end user licen", r"end user licen[sc]e agreement"),
    ("eula", "by installing", r"by installing copying or otherwise using (?:the|this) software you agree"),
    ("no-copying", "may not be reproduced", r"may not be reproduced(?: or (?:copied|distributed))? without (?:prior |the )?(?:written )?(?:permission|consent)"),
    ("no-copying", "no part of this", r"no part of this (?:book|publication|document|work|site) may be (?:reproduced|copied|transmitted|stored)"),
    ("non-commercial", "non commercial use only", r"for (?:personal )?non commercial use only"),
    ("non-commercial", "personal use only", r"for personal use only"),
    ("research-only", "research purposes only", r"for (?:academic |non commercial )?research purposes only"),
    ("evaluation-only", "evaluation purposes only", r"for evaluation purposes only"),
    ("freeware", "this software is freeware", r"this software is freeware"),
    ("shareware", "this is shareware", r"this is shareware"),
)
