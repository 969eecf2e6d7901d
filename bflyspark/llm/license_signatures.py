"""Hand-written licence signatures: label, expression over lower-case words, keyword, confidence.

Words are joined by single blanks, so punctuation never stands in an expression. The keyword is a word or
phrase that every match holds. Entries are grouped by a stem that every match holds too; texts without any
stem are passed over at once.
"""

# Signatures by stem.
SIGNATURES: dict[str, list[tuple[str, str, str, float]]] = {
    "permission": [
        ("mit", r"permission is hereby granted free of charge to any person", "hereby", 0.98),
        ("mit", r"the above copyright notice and this permission notice shall be included in all copies", "notice", 0.97),
        ("x11", r"permission to use copy modify distribute and sell this software", "permission", 0.94),
        ("isc", r"permission to use copy modify and or distribute this software", "permission", 0.97),
        ("isc", r"permission to use copy modify and distribute this software for any purpose with or without fee", "permission", 0.96),
        ("hpnd", r"permission to use copy modify and distribute this software and its documentation", "permission", 0.93),
        ("postgresql", r"permission to use copy modify and distribute this software and its documentation for any purpose without fee and without a written agreement", "permission", 0.97),
        ("ofl", r"permission is hereby granted free of charge to any person obtaining a copy of the font software", "font", 0.98),
        ("unicode", r"permission is hereby granted free of charge to any person obtaining a copy of the unicode data files", "unicode", 0.98),
        ("ntp", r"permission to use copy modify and distribute this software and its documentation for any purpose with or without fee is hereby granted", "hereby", 0.95),
        ("zlib", r"permission is granted to anyone to use this software for any purpose", "anyone", 0.97),
        ("gfdl", r"permission is granted to copy distribute and or modify this document under the terms", "granted", 0.95),
        ("verbatim", r"permission is granted to make and distribute verbatim copies", "verbatim", 0.9),
        ("fsf-permissive", r"copying and distribution of this file with or without modification are permitted in any medium without royalty provided the copyright notice and this notice are preserved with permission", "royalty", 0.9),
        ("curl", r"permission to use copy modify and distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice", "hereby", 0.96),
        ("no-reprint", r"(?:reprinted|reproduced|used) (?:here )?with (?:the )?(?:kind )?permission", "with", 0.6),
        ("no-reprint", r"may not be (?:reproduced|reprinted|copied|republished) without (?:the )?(?:prior )?(?:written )?permission", "without", 0.85),
        ("no-reprint", r"without (?:the )?(?:express|prior) (?:written )?permission of the (?:publisher|author|copyright (?:holder|owner))", "without", 0.85),
        ("cc-by-nc", r"permission beyond the scope of this licen[sc]e", "scope", 0.7),
    ],
    "redistribut": [
        ("bsd", r"redistribution and use in source and binary forms", "redistribution", 0.98),
        ("bsd", r"redistributions of source code must retain the above copyright notice", "redistributions", 0.97),
        ("bsd", r"redistributions in binary form must reproduce the above copyright notice", "redistributions", 0.97),
        ("redistributable", r"(?:freely|may be freely) redistributable", "redistributable", 0.6),
        ("no-redistribution", r"(?:may|must) not be redistributed", "redistributed", 0.75),
        ("no-redistribution", r"redistribution (?:is )?(?:strictly )?prohibited", "redistribution", 0.8),
        ("gpl", r"this program is free software you can redistribute it and or modify it under the terms of the gnu general public licen[sc]e", "redistribute", 0.97),
        ("lgpl", r"this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public licen[sc]e", "redistribute", 0.97),
        ("agpl", r"this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public licen[sc]e", "redistribute", 0.97),
        ("artistic", r"you may redistribute this (?:program|package|module) under the same terms as perl itself", "perl", 0.93),
        ("perl", r"(?:redistribute|redistributed) (?:it |them )?(?:and or modify it )?under the same terms as perl", "perl", 0.9),
        ("beerware", r"as long as you retain this notice you can redistribute", "notice", 0.8),
    ],
    "licen": [
        ("mit", r"(?:the )?mit licen[sc]e", "mit", 0.9),
        ("mit", r"licensed under (?:the )?mit", "mit", 0.85),
        ("mit", r"expat licen[sc]e", "expat", 0.88),
        ("mit-0", r"mit no attribution licen[sc]e", "attribution", 0.92),
        ("x11", r"x11 licen[sc]e", "x11", 0.9),
        ("isc", r"isc licen[sc]e", "isc", 0.9),
        ("bsd-3-clause", r"new bsd licen[sc]e", "bsd", 0.92),
        ("bsd-3-clause", r"modified bsd licen[sc]e", "bsd", 0.92),
        ("bsd-3-clause", r"revised bsd licen[sc]e", "bsd", 0.92),
        ("bsd-3-clause", r"(?:bsd 3 clause|3 clause bsd) licen[sc]e", "bsd", 0.94),
        ("bsd-2-clause", r"simplified bsd licen[sc]e", "bsd", 0.92),
        ("bsd-2-clause", r"freebsd licen[sc]e", "freebsd", 0.92),
        ("bsd-2-clause", r"(?:bsd 2 clause|2 clause bsd) licen[sc]e", "bsd", 0.94),
        ("bsd-4-clause", r"original bsd licen[sc]e", "bsd", 0.92),
        ("bsd-1-clause", r"bsd 1 clause licen[sc]e", "bsd", 0.94),
        ("0bsd", r"(?:bsd zero clause|zero clause bsd) licen[sc]e", "bsd", 0.95),
        ("0bsd", r"0bsd licen[sc]e", "0bsd", 0.95),
        ("bsd", r"bsd(?: style)? licen[sc]e", "bsd", 0.8),
        ("bsd", r"berkeley software distribution licen[sc]e", "berkeley", 0.88),
        ("zlib", r"zlib licen[sc]e", "zlib", 0.9),
        ("zlib", r"zlib libpng licen[sc]e", "libpng", 0.92),
        ("libpng", r"png reference library licen[sc]e", "png", 0.92),
        ("wtfpl", r"do what the fuck you want to public licen[sc]e", "fuck", 0.98),
        ("wtfpl", r"wtfpl licen[sc]e", "wtfpl", 0.95),
        ("psf", r"python software foundation licen[sc]e", "python", 0.92),
        ("psf", r"psf licen[sc]e(?: agreement)?", "psf", 0.88),
        ("python", r"cnri (?:open source )?licen[sc]e agreement", "cnri", 0.92),
        ("php", r"(?:the )?php licen[sc]e(?: version 3 0[01])?", "php", 0.9),
        ("ruby", r"(?:the )?ruby licen[sc]e", "ruby", 0.85),
        ("perl", r"same licen[sc]e as perl", "perl", 0.88),
        ("artistic", r"clarified artistic licen[sc]e", "clarified", 0.93),
        ("openssl", r"(?:the )?openssl licen[sc]e", "openssl", 0.93),
        ("ssleay", r"original ssleay licen[sc]e", "ssleay", 0.95),
        ("curl", r"(?:the )?curl licen[sc]e", "curl", 0.88),
        ("postgresql", r"(?:the )?postgresql licen[sc]e", "postgresql", 0.93),
        ("ncsa", r"university of illinois ncsa open source licen[sc]e", "illinois", 0.96),
        ("ncsa", r"ncsa licen[sc]e", "ncsa", 0.9),
        ("ecl", r"educational community licen[sc]e(?: version)?(?: [12] 0)?", "educational", 0.93),
        ("afl", r"academic free licen[sc]e(?: version)?(?: [123] [01])?", "academic", 0.93),
        ("apsl", r"apple public source licen[sc]e(?: version)?(?: [12] [012])?", "apple", 0.94),
        ("apple-sample", r"apple sample code licen[sc]e", "apple", 0.92),
        ("cpl", r"common public licen[sc]e(?: version)?(?: 1 0)?", "common", 0.92),
        ("cpal", r"common public attribution licen[sc]e(?: version)?(?: 1 0)?", "attribution", 0.94),
        ("ipl", r"ibm public licen[sc]e(?: version)?(?: 1 0)?", "ibm", 0.94),
        ("intel", r"intel open source licen[sc]e", "intel", 0.93),
        ("intel-simplified", r"intel simplified software licen[sc]e", "intel", 0.94),
        ("lucent", r"lucent public licen[sc]e(?: version)?(?: 1 0[12]?)?", "lucent", 0.94),
        ("ms-pl", r"microsoft public licen[sc]e", "microsoft", 0.94),
        ("ms-rl", r"microsoft reciprocal licen[sc]e", "reciprocal", 0.95),
        ("ms-eula", r"microsoft software licen[sc]e terms", "microsoft", 0.93),
        ("nasa", r"nasa open source agreement licen[sc]e", "nasa", 0.92),
        ("nokia", r"nokia open source licen[sc]e", "nokia", 0.94),
        ("npl", r"netscape public licen[sc]e(?: version)?(?: 1 [01])?", "netscape", 0.94),
        ("qpl", r"q public licen[sc]e(?: version)?(?: 1 0)?", "q", 0.92),
        ("rpl", r"reciprocal public licen[sc]e(?: version)?(?: 1 [15])?", "reciprocal", 0.93),
        ("rpsl", r"realnetworks public source licen[sc]e", "realnetworks", 0.95),
        ("sissl", r"sun industry standards source licen[sc]e", "sun", 0.94),
        ("spl", r"sun public licen[sc]e", "sun", 0.93),
        ("bcl", r"oracle binary code licen[sc]e agreement", "oracle", 0.94),
        ("otn", r"oracle technology network licen[sc]e", "oracle", 0.93),
        ("upl", r"universal permissive licen[sc]e(?: version| v)?(?: 1 0)?", "permissive", 0.94),
        ("sleepycat", r"(?:the )?sleepycat licen[sc]e", "sleepycat", 0.95),
        ("watcom", r"sybase open watcom public licen[sc]e", "watcom", 0.95),
        ("w3c", r"w3c software (?:notice and )?licen[sc]e", "w3c", 0.94),
        ("w3c", r"w3c document licen[sc]e", "w3c", 0.93),
        ("xnet", r"x net licen[sc]e", "net", 0.85),
        ("zpl", r"zope public licen[sc]e(?: version)?(?: [12] [01])?", "zope", 0.95),
        ("vim", r"(?:the )?vim licen[sc]e", "vim", 0.9),
        ("tcl", r"tcl tk licen[sc]e", "tcl", 0.92),
        ("unlicense", r"(?:released|licensed) under the unlicense", "unlicense", 0.95),
        ("latex", r"latex project public licen[sc]e(?: version)?(?: 1 [0123])?", "latex", 0.95),
        ("lppl", r"lppl licen[sc]e", "lppl", 0.92),
        ("ofl", r"sil open font licen[sc]e(?: version)?(?: 1 [01])?", "sil", 0.96),
        ("ofl", r"open font licen[sc]e", "font", 0.9),
        ("ubuntu-font", r"ubuntu font licen[sc]e", "ubuntu", 0.95),
        ("bitstream", r"bitstream vera fonts? licen[sc]e", "bitstream", 0.94),
        ("gust-font", r"gust font licen[sc]e", "gust", 0.95),
        ("odbl", r"open (?:data commons open )?database licen[sc]e", "database", 0.94),
        ("odc-by", r"open data commons attribution licen[sc]e", "commons", 0.95),
        ("pddl", r"public domain dedication and licen[sc]e", "dedication", 0.95),
        ("cdla-permissive", r"community data licen[sc]e agreement permissive", "permissive", 0.95),
        ("cdla-sharing", r"community data licen[sc]e agreement sharing", "sharing", 0.95),
        ("ogl", r"open government licen[sc]e(?: v)?(?: ?[123](?: 0)?)?", "government", 0.94),
        ("ogl-canada", r"open government licen[sc]e canada", "canada", 0.95),
        ("etalab", r"licence ouverte(?: open licence)?", "ouverte", 0.9),
        ("nlod", r"norwegian licen[sc]e for open government data", "norwegian", 0.95),
        ("cecill", r"cecill(?: [abc])? (?:free software )?licen[sc]e(?: agreement)?", "cecill", 0.95),
        ("cern-ohl", r"cern open hardware licen[sc]e(?: version)?(?: [12](?: [012])?)?", "cern", 0.95),
        ("tapr-ohl", r"tapr open hardware licen[sc]e", "tapr", 0.95),
        ("solderpad", r"solderpad hardware licen[sc]e", "solderpad", 0.95),
        ("sspl", r"server side public licen[sc]e(?: version)?(?: 1)?", "server", 0.95),
        ("elastic", r"elastic licen[sc]e(?: version)?(?: 2(?: 0)?)?", "elastic", 0.93),
        ("confluent", r"confluent community licen[sc]e", "confluent", 0.95),
        ("busl", r"business source licen[sc]e(?: version)?(?: 1 1)?", "business", 0.95),
        ("redis", r"redis source available licen[sc]e", "redis", 0.95),
        ("commons-clause", r"commons clause licen[sc]e condition", "clause", 0.95),
        ("polyform", r"polyform (?:noncommercial|small business|perimeter|shield|strict|internal use) licen[sc]e", "polyform", 0.95),
        ("prosperity", r"prosperity public licen[sc]e", "prosperity", 0.94),
        ("parity", r"parity public licen[sc]e", "parity", 0.94),
        ("hippocratic", r"hippocratic licen[sc]e", "hippocratic", 0.95),
        ("json", r"(?:the )?json licen[sc]e", "json", 0.85),
        ("rail", r"(?:open|creativeml open) rail(?: m)? licen[sc]e", "rail", 0.92),
        ("llama", r"llama (?:[23] )?community licen[sc]e", "llama", 0.93),
        ("blue-oak", r"blue oak model licen[sc]e", "oak", 0.95),
        ("bzip2", r"bzip2 licen[sc]e", "bzip2", 0.92),
        ("ftl", r"freetype (?:project )?licen[sc]e", "freetype", 0.95),
        ("ijg", r"independent jpeg group licen[sc]e", "jpeg", 0.92),
        ("libtiff", r"libtiff licen[sc]e", "libtiff", 0.92),
        ("icu", r"icu licen[sc]e", "icu", 0.9),
        ("unicode", r"unicode (?:inc )?licen[sc]e agreement", "unicode", 0.94),
        ("info-zip", r"info zip licen[sc]e", "zip", 0.92),
        ("imagemagick", r"imagemagick licen[sc]e", "imagemagick", 0.94),
        ("jasper", r"jasper licen[sc]e", "jasper", 0.9),
        ("mulan", r"mulan (?:permissive software|public) licen[sc]e", "mulan", 0.95),
        ("nethack", r"nethack general public licen[sc]e", "nethack", 0.95),
        ("ngpl", r"nethack licen[sc]e", "nethack", 0.9),
        ("osgi", r"osgi specification licen[sc]e", "osgi", 0.93),
        ("opl", r"open publication licen[sc]e(?: v)?(?: 1 0)?", "publication", 0.92),
        ("oclc", r"oclc research public licen[sc]e", "oclc", 0.95),
        ("motosoto", r"motosoto open source licen[sc]e", "motosoto", 0.95),
        ("ncbi", r"ncbi public domain notice licen[sc]e", "ncbi", 0.9),
        ("eiffel", r"eiffel forum licen[sc]e(?: version)?(?: [12])?", "eiffel", 0.95),
        ("entessa", r"entessa public licen[sc]e", "entessa", 0.95),
        ("erlang", r"erlang public licen[sc]e(?: version)?(?: 1 1)?", "erlang", 0.95),
        ("fair", r"(?:the )?fair licen[sc]e", "fair", 0.75),
        ("frameworx", r"frameworx open licen[sc]e", "frameworx", 0.95),
        ("free-art", r"free art licen[sc]e", "art", 0.9),
        ("against-drm", r"against drm licen[sc]e", "drm", 0.92),
        ("design-science", r"design science licen[sc]e", "science", 0.9),
        ("proprietary", r"end user licen[sc]e agreement", "user", 0.8),
        ("proprietary", r"proprietary licen[sc]e", "proprietary", 0.8),
        ("proprietary", r"commercial licen[sc]e (?:is )?required", "commercial", 0.8),
        ("dual", r"dual licensed under", "dual", 0.75),
        ("royalty-free", r"royalty free licen[sc]e", "royalty", 0.7),
        ("royalty-free", r"worldwide royalty free (?:non exclusive|nonexclusive|perpetual) licen[sc]e", "worldwide", 0.75),
        ("site-terms", r"you retain all (?:ownership )?rights (?:in|to) your content and grant (?:us )?a licen[sc]e", "retain", 0.7),
        ("cc", r"creative commons licen[sc]e", "creative", 0.85),
        ("cc", r"licensed under (?:a )?creative commons", "creative", 0.88),
        ("cc-by-sa", r"text is available under the creative commons attribution share ?alike licen[sc]e", "creative", 0.95),
    ],
    "warrant": [
        ("as-is", r"(?:the software|this software) is provided as is without warranty of any kind", "without", 0.85),
        ("as-is", r"without any express or implied warranty", "implied", 0.8),
        ("as-is", r"provided as is without (?:express or implied )?warranty", "without", 0.8),
        ("gpl", r"but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose", "merchantability", 0.85),
        ("apache", r"on an as is basis without warranties or conditions of any kind", "warranties", 0.93),
        ("bsd", r"any express or implied warranties including but not limited to the implied warranties of merchantability", "merchantability", 0.85),
        ("mpl", r"covered software is provided under this licen[sc]e on an as is basis without warranty", "covered", 0.93),
    ],
    "source": [
        ("zlib", r"altered source versions must be plainly marked as such", "altered", 0.97),
        ("mpl", r"this source code form is subject to the terms of the mozilla public licen[sc]e", "mozilla", 0.98),
        ("gpl", r"source code must be made available under the same terms", "terms", 0.7),
    ],
    "software": [
        ("unlicense", r"this is free and unencumbered software released into the public domain", "unencumbered", 0.98),
        ("boost", r"boost software licen[sc]e version 1 0 august 17th 2003", "boost", 0.98),
        ("zlib", r"the origin of this software must not be misrepresented", "misrepresented", 0.97),
        ("json", r"the software shall be used for good not evil", "evil", 0.98),
        ("free-software", r"this (?:program|library) is free software", "free", 0.7),
        ("apache", r"this product includes software developed by the apache software foundation", "apache", 0.95),
        ("openssl", r"this product includes software developed by the openssl project", "openssl", 0.95),
        ("bsd-4-clause", r"all advertising materials mentioning features or use of this software must display", "advertising", 0.97),
        ("bsd-4-clause", r"this product includes software developed by the university of california", "california", 0.96),
        ("ijg", r"this software is based in part on the work of the independent jpeg group", "jpeg", 0.96),
        ("ftl", r"portions of this software are copyright (?:19|20)[0-9]{2} the freetype project", "freetype", 0.96),
    ],
    "domain": [
        ("public-domain", r"released into the public domain", "domain", 0.88),
        ("public-domain", r"(?:dedicated|placed) (?:in|into|to) the public domain", "domain", 0.87),
        ("public-domain", r"(?:is|are|now|being) in the public domain", "domain", 0.75),
        ("public-domain", r"the author (?:hereby )?disclaims copyright to this source code public domain", "disclaims", 0.85),
        ("cc-pdm", r"public domain mark(?: 1 0)?", "domain", 0.85),
        ("cc0", r"public domain dedication", "dedication", 0.8),
        ("public-domain-us", r"work of the u s government (?:and )?(?:is )?(?:therefore )?(?:not subject to copyright|in the public domain) public domain", "government", 0.8),
        ("public-domain", r"public domain", "domain", 0.6),
    ],
    "reserved": [
        ("reserved", r"all rights reserved", "reserved", 0.7),
        ("some-reserved", r"some rights reserved", "reserved", 0.75),
        ("no-reserved", r"no rights reserved", "reserved", 0.8),
    ],
    "copyright": [
        ("copyright", r"copyright (?:c )?(?:1[89][0-9]{2}|20[0-9]{2})", "copyright", 0.5),
        ("copyright", r"copyrighted (?:material|work)", "copyrighted", 0.5),
        ("no-copyright", r"no copyright(?: infringement)? intended", "intended", 0.6),
        ("copyleft", r"copyright and copyleft", "copyleft", 0.6),
        ("public-domain-us", r"not subject to copyright protection in the united states", "protection", 0.85),
        ("fair-use", r"copyright act (?:of )?1976 allowance is made for fair use", "allowance", 0.8),
        ("crown", r"crown copyright", "crown", 0.8),
    ],
    "proprietary": [
        ("proprietary", r"confidential and proprietary", "proprietary", 0.85),
        ("proprietary", r"proprietary and confidential", "proprietary", 0.85),
        ("proprietary", r"proprietary information of", "proprietary", 0.75),
        ("trade-secret", r"contains (?:proprietary )?trade secrets? (?:and|or) proprietary information", "trade", 0.85),
    ],
    "unauthori": [
        ("proprietary", r"unauthorized (?:copying|reproduction|distribution)", "unauthorized", 0.8),
        ("proprietary", r"unauthorised (?:copying|reproduction|distribution)", "unauthorised", 0.8),
        ("proprietary", r"unauthorized (?:use|duplication|disclosure) (?:of this|is) (?:material|document|prohibited|strictly prohibited)", "unauthorized", 0.8),
    ],
    "personal": [
        ("noncommercial", r"for personal (?:and )?non ?commercial use(?: only)?", "personal", 0.75),
        ("noncommercial", r"for personal use only", "personal", 0.7),
    ],
    "vorbehalten": [("reserved", r"alle rechte vorbehalten", "vorbehalten", 0.7)],
    "droits": [("reserved", r"tous droits réservés", "droits", 0.7), ("reserved", r"tous les droits sont réservés", "droits", 0.7)],
    "derechos": [("reserved", r"todos los derechos reservados", "derechos", 0.7), ("reserved", r"reservados todos los derechos", "derechos", 0.7)],
    "diritti": [("reserved", r"tutti i diritti(?: sono)? riservati", "diritti", 0.7)],
    "direitos": [("reserved", r"todos os direitos reservados", "direitos", 0.7)],
    "dominio": [("public-domain", r"(?:de|en el) dominio público", "dominio", 0.6)],
}
