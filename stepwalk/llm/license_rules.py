"""The ordered signature rules of the license scan, over texts reduced to lower-case words between single spaces."""

from __future__ import annotations

# Base phrases and their labels.
BASE = (("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc"))

# Verbs that, before "under", offer a text on terms.
OFFERS = ("licensed", "released", "distributed", "available", "provided", "published", "use")

# Keywords that stand inside longer words too.
LOOSE = ("gpl", "lgpl", "agpl", "bsd", "odbl", "rail")

# Signatures in the order in which they are tried: label, a word that every match holds, pattern, priority (4 wins
# over 1), confidence.  Names and tags of a license, sentences of its notice, sentences of its text, addresses of its text.
SIGNATURES = (
    # MIT and its kin
    ("mit", "spdx", r"spdx license identifier mit", 4, 1.0),
    ("mit", "mit", r"licensed under (?:the )?(?:terms of (?:the )?)?mit(?: x11| expat)?(?: open source)?(?: license| licence)?", 4, 0.98),
    ("mit", "mit", r"(?:released|distributed|available|provided|published|free to use|dual licensed) under (?:the )?(?:terms of (?:the )?)?mit(?: x11| expat)?(?: license| licence)?", 3, 0.95),
    ("mit", "mit", r"(?:subject to|governed by|covered by|see) (?:the )?(?:terms of (?:the )?)?mit (?:license|licence)", 3, 0.9),
    ("mit", "mit", r"license mit", 2, 0.85),
    ("mit", "mit", r"(?:the )?mit (?:license|licence)", 2, 0.8),
    ("mit", "expat", r"expat (?:license|licence)", 2, 0.8),
    ("mit", "granted", r"permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", 4, 0.99),
    ("mit", "granted", r"permission is hereby granted free of charge to any person obtaining a copy", 4, 0.97),
    ("mit", "notice", r"the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software", 4, 0.97),
    ("mit", "opensource", r"opensource org licenses mit(?: license)?(?: php)?", 3, 0.95),
    ("mit-0", "spdx", r"spdx license identifier mit 0", 4, 1.0),
    ("mit-0", "attribution", r"mit no attribution(?: license)?", 4, 0.95),
    ("x11", "x11", r"(?:the )?x11 (?:license|licence)", 2, 0.8),
    ("x11", "consortium", r"except as contained in this notice the name of the x consortium shall not be used in advertising", 4, 0.98),
    ("jsnlog-good-not-evil", "evil", r"the software shall be used for good not evil", 4, 0.98),
    # Apache
    ("apache-2", "spdx", r"spdx license identifier apache 2 0", 4, 1.0),
    ("apache-2", "apache", r"licensed under (?:the )?(?:terms of (?:the )?)?apache(?: software)?(?: license)?(?: version| v)? 2(?: 0)?(?: license)?", 4, 0.98),
    ("apache-2", "apache", r"(?:released|distributed|available|provided|published|free to use|dual licensed) under (?:the )?(?:terms of (?:the )?)?apache(?: software)?(?: license)?(?: version| v)? 2(?: 0)?(?: terms| license)?", 3, 0.95),
    ("apache-2", "apache", r"apache(?: software)? license(?: version| v)? 2(?: 0)?", 3, 0.92),
    ("apache-2", "apache", r"apache 2(?: 0)? (?:license|licence)", 2, 0.85),
    ("apache-2", "apache", r"license apache 2(?: 0)?", 2, 0.85),
    ("apache-2", "apache", r"www apache org licenses license 2 0", 3, 0.97),
    ("apache-2", "compliance", r"you may not use this file except in compliance with the license", 3, 0.9),
    ("apache-2", "contributor", r"subject to the terms and conditions of this license each contributor hereby grants to you a perpetual worldwide non exclusive no charge royalty free irrevocable copyright license", 4, 0.99),
    ("apache-1", "spdx", r"spdx license identifier apache 1 [01]", 4, 1.0),
    ("apache-1", "apache", r"apache(?: software)? license(?: version| v)? 1(?: [01])?", 3, 0.92),
    ("apache-1", "apache", r"the names apache server and apache group must not be used to endorse or promote products derived from this software without prior written permission", 4, 0.98),
    # BSD
    ("0bsd", "spdx", r"spdx license identifier 0bsd", 4, 1.0),
    ("0bsd", "0bsd", r"(?:license|under) 0bsd", 3, 0.95),
    ("0bsd", "zero", r"zero clause bsd(?: license)?", 3, 0.95),
    ("0bsd", "0bsd", r"0bsd license", 3, 0.95),
    ("bsd-2", "spdx", r"spdx license identifier bsd 2 clause", 4, 1.0),
    ("bsd-2", "bsd", r"licensed under (?:the )?(?:simplified bsd|freebsd|bsd 2 clause|2 clause bsd)(?: license)?", 4, 0.97),
    ("bsd-2", "bsd", r"(?:released|distributed|available|provided|published) under (?:the )?(?:simplified bsd|freebsd|bsd 2 clause|2 clause bsd)(?: license)?", 3, 0.95),
    ("bsd-2", "bsd", r"(?:simplified bsd|bsd 2 clause|2 clause bsd|two clause bsd) (?:license|licence)", 3, 0.9),
    ("bsd-2", "freebsd", r"freebsd (?:license|licence)", 2, 0.85),
    ("bsd-3", "spdx", r"spdx license identifier bsd 3 clause(?: clear)?", 4, 1.0),
    ("bsd-3", "bsd", r"licensed under (?:the )?(?:new bsd|revised bsd|modified bsd|bsd 3 clause|3 clause bsd)(?: license)?", 4, 0.97),
    ("bsd-3", "bsd", r"(?:released|distributed|available|provided|published) under (?:the )?(?:new bsd|revised bsd|modified bsd|bsd 3 clause|3 clause bsd)(?: license)?", 3, 0.95),
    ("bsd-3", "bsd", r"(?:new bsd|revised bsd|modified bsd|bsd 3 clause|3 clause bsd|three clause bsd) (?:license|licence)", 3, 0.9),
    ("bsd-3", "endorse", r"nor the names of its contributors may be used to endorse or promote products derived from this software", 4, 0.98),
    ("bsd-4", "spdx", r"spdx license identifier bsd 4 clause", 4, 1.0),
    ("bsd-4", "bsd", r"(?:original bsd|bsd 4 clause|4 clause bsd) (?:license|licence)", 3, 0.9),
    ("bsd-4", "advertising", r"all advertising materials mentioning features or use of this software must display the following acknowledgement", 4, 0.98),
    ("bsd", "bsd", r"(?:licensed|released|distributed|available) under (?:the |a )?bsd(?: style)?(?: license| licence)?", 2, 0.8),
    ("bsd", "bsd", r"bsd(?: style)? (?:license|licence)", 1, 0.7),
    ("bsd", "redistribution", r"redistribution and use in source and binary forms with or without modification are permitted", 3, 0.95),
    ("bsd", "redistributions", r"redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer", 3, 0.95),
    # GNU General Public License
    ("gpl-1", "spdx", r"spdx license identifier gpl 1 0(?: only| or later)?", 4, 1.0),
    ("gpl-1", "general", r"gnu general public license(?: version| v) 1(?: 0)?", 3, 0.92),
    ("gpl-2", "spdx", r"spdx license identifier gpl 2 0(?: only| or later| with classpath exception 2 0)?", 4, 1.0),
    ("gpl-2", "gpl", r"licensed under (?:the )?(?:terms of (?:the )?)?(?:gnu )?gpl(?: version| v)? ?2(?: 0)?(?: license| only| or later)?", 4, 0.97),
    ("gpl-2", "gpl", r"(?:released|distributed|available|provided|published|free to use|dual licensed) under (?:the )?(?:terms of (?:the )?)?(?:gnu )?gpl(?: version| v)? ?2(?: 0)?", 3, 0.95),
    ("gpl-2", "gpl", r"(?:gnu )?gpl(?: version| v)? ?2(?: 0)? (?:license|licence)", 3, 0.9),
    ("gpl-2", "gpl", r"license (?:gnu )?gpl(?: version| v)? ?2(?: 0)?", 3, 0.9),
    ("gpl-2", "general", r"gnu general public license(?: as published by the free software foundation)?(?: either)?(?: version| v) 2(?: of the license)?", 3, 0.95),
    ("gpl-2", "june", r"gnu general public license version 2 june 1991", 4, 0.99),
    ("gpl-3", "spdx", r"spdx license identifier gpl 3 0(?: only| or later)?", 4, 1.0),
    ("gpl-3", "gpl", r"licensed under (?:the )?(?:terms of (?:the )?)?(?:gnu )?gpl(?: version| v)? ?3(?: 0)?(?: license| only| or later)?", 4, 0.97),
    ("gpl-3", "gpl", r"(?:released|distributed|available|provided|published|free to use|dual licensed) under (?:the )?(?:terms of (?:the )?)?(?:gnu )?gpl(?: version| v)? ?3(?: 0)?", 3, 0.95),
    ("gpl-3", "gpl", r"(?:gnu )?gpl(?: version| v)? ?3(?: 0)? (?:license|licence)", 3, 0.9),
    ("gpl-3", "gpl", r"license (?:gnu )?gpl(?: version| v)? ?3(?: 0)?", 3, 0.9),
    ("gpl-3", "general", r"gnu general public license(?: as published by the free software foundation)?(?: either)?(?: version| v) 3(?: of the license)?", 3, 0.95),
    ("gpl-3", "june", r"gnu general public license version 3 29 june 2007", 4, 0.99),
    ("gpl", "gpl", r"(?:licensed|released|distributed|available) under (?:the )?(?:terms of (?:the )?)?(?:gnu )?gpl", 2, 0.8),
    ("gpl", "general", r"gnu general public (?:license|licence)", 1, 0.75),
    ("gpl", "redistribute", r"this program is free software you can redistribute it and or modify it under the terms of the gnu general public license", 3, 0.95),
    ("gpl", "merchantability", r"without even the implied warranty of merchantability or fitness for a particular purpose see the gnu general public license for more details", 3, 0.95),
    ("gpl", "received", r"you should have received a copy of the gnu general public license along with this program", 3, 0.95),
    ("gpl", "gnu", r"www gnu org licenses(?: gpl)?(?: html)?", 1, 0.7),
    ("gpl-classpath", "classpath", r"gnu classpath exception|classpath exception to the gnu general public license", 4, 0.95),
    ("gpl-linking", "openssl", r"permission to link the code of portions of this program with the openssl library", 4, 0.9),
    # GNU Lesser, Affero and Free Documentation
    ("lgpl-2", "spdx", r"spdx license identifier lgpl 2 [01](?: only| or later)?", 4, 1.0),
    ("lgpl-2", "lgpl", r"(?:licensed|released|distributed|available) under (?:the )?(?:terms of (?:the )?)?(?:gnu )?lgpl(?: version| v)? ?2(?: [01])?", 3, 0.95),
    ("lgpl-2", "lgpl", r"(?:gnu )?lgpl(?: version| v)? ?2(?: [01])? (?:license|licence)", 3, 0.9),
    ("lgpl-2", "lesser", r"gnu lesser general public license(?: as published by the free software foundation either)?(?: version| v) 2(?: [01])?", 3, 0.95),
    ("lgpl-2", "library", r"gnu library general public license(?: version| v)? ?(?:2(?: [01])?)?", 3, 0.92),
    ("lgpl-3", "spdx", r"spdx license identifier lgpl 3 0(?: only| or later)?", 4, 1.0),
    ("lgpl-3", "lgpl", r"(?:licensed|released|distributed|available) under (?:the )?(?:terms of (?:the )?)?(?:gnu )?lgpl(?: version| v)? ?3(?: 0)?", 3, 0.95),
    ("lgpl-3", "lgpl", r"(?:gnu )?lgpl(?: version| v)? ?3(?: 0)? (?:license|licence)", 3, 0.9),
    ("lgpl-3", "lesser", r"gnu lesser general public license(?: as published by the free software foundation either)?(?: version| v) 3", 3, 0.95),
    ("lgpl", "lesser", r"gnu lesser general public (?:license|licence)", 1, 0.75),
    ("lgpl", "lgpl", r"(?:licensed|released|distributed|available) under (?:the )?(?:gnu )?lgpl", 2, 0.8),
    ("agpl-3", "spdx", r"spdx license identifier agpl 3 0(?: only| or later)?", 4, 1.0),
    ("agpl-3", "agpl", r"(?:licensed|released|distributed|available) under (?:the )?(?:terms of (?:the )?)?(?:gnu )?agpl(?: version| v)? ?3(?: 0)?", 3, 0.95),
    ("agpl-3", "agpl", r"(?:gnu )?agpl(?: version| v)? ?3(?: 0)? (?:license|licence)", 3, 0.9),
    ("agpl-3", "affero", r"gnu affero general public license(?: as published by the free software foundation either)?(?: version| v)? 3", 3, 0.95),
    ("agpl", "affero", r"gnu affero general public (?:license|licence)", 1, 0.75),
    ("agpl", "remotely", r"all users interacting with it remotely through a computer network", 4, 0.97),
    ("gfdl-1", "spdx", r"spdx license identifier gfdl 1 [123](?: only| or later)?", 4, 1.0),
    ("gfdl-1", "documentation", r"gnu free documentation license(?: version| v)? ?(?:1 [123])?", 3, 0.92),
    ("gfdl-1", "invariant", r"with no invariant sections no front cover texts and no back cover texts", 4, 0.95),
    # Weak copyleft of foundations and companies
    ("mpl-1", "spdx", r"spdx license identifier mpl 1 [01]", 4, 1.0),
    ("mpl-1", "mozilla", r"mozilla public license(?: version| v)? 1 [01]", 3, 0.95),
    ("mpl-1", "www", r"www mozilla org mpl mpl 1 1", 3, 0.93),
    ("mpl-2", "spdx", r"spdx license identifier mpl 2 0", 4, 1.0),
    ("mpl-2", "mozilla", r"mozilla public license(?: version| v)? 2 0", 3, 0.95),
    ("mpl-2", "mpl", r"(?:licensed|released|distributed|available) under (?:the )?mpl(?: version| v)? 2(?: 0)?", 3, 0.93),
    ("mpl-2", "mozilla", r"if a copy of the mpl was not distributed with this file you can obtain one at (?:https? )?mozilla org mpl 2 0", 4, 0.98),
    ("mpl", "mozilla", r"mozilla public (?:license|licence)", 1, 0.75),
    ("epl-1", "spdx", r"spdx license identifier epl 1 0", 4, 1.0),
    ("epl-1", "eclipse", r"eclipse public license(?: version| v)? ?1(?: 0)?", 3, 0.95),
    ("epl-1", "eclipse", r"www eclipse org legal epl v10 html", 3, 0.93),
    ("epl-2", "spdx", r"spdx license identifier epl 2 0", 4, 1.0),
    ("epl-2", "eclipse", r"eclipse public license(?: version| v)? ?2(?: 0)?", 3, 0.95),
    ("epl-2", "eclipse", r"www eclipse org legal epl 2 0", 3, 0.93),
    ("edl-1", "eclipse", r"eclipse distribution license(?: version| v)? ?1(?: 0)?", 3, 0.93),
    ("cddl-1", "spdx", r"spdx license identifier cddl 1 [01]", 4, 1.0),
    ("cddl-1", "distribution", r"common development and distribution license(?: version| v)?(?: 1(?: [01])?)?", 3, 0.95),
    ("cddl-1", "cddl", r"(?:licensed|released|distributed|available) under (?:the )?cddl(?: version| v)?(?: 1(?: [01])?)?", 3, 0.92),
    ("cddl-1", "cddl", r"cddl (?:license|licence)", 2, 0.85),
    ("cpl-1", "common", r"common public license(?: version| v)?(?: 1(?: 0)?)?", 3, 0.92),
    ("ipl-1", "ibm", r"ibm public license(?: version| v)?(?: 1(?: 0)?)?", 3, 0.92),
    ("eupl-1", "spdx", r"spdx license identifier eupl 1 [012]", 4, 1.0),
    ("eupl-1", "european", r"european union public (?:license|licence)(?: version| v)?(?: 1 [012])?", 3, 0.95),
    ("eupl-1", "eupl", r"(?:licensed|released|distributed|available) under (?:the )?eupl(?: version| v)?(?: 1 [012])?", 3, 0.93),
    ("osl-3", "spdx", r"spdx license identifier osl 3 0", 4, 1.0),
    ("osl-3", "open", r"open software license(?: version| v)? ?3(?: 0)?", 3, 0.93),
    ("afl-3", "academic", r"academic free license(?: version| v)?(?: 3(?: 0)?)?", 3, 0.93),
    ("cecill-2", "cecill", r"cecill(?: free software)? license(?: agreement)?", 3, 0.9),
    ("cecill-2", "cecill", r"(?:governed by|under) the cecill(?: b| c)? license", 4, 0.95),
    ("qpl-1", "public", r"q public license(?: version| v)?(?: 1(?: 0)?)?", 3, 0.92),
    ("sleepycat", "sleepycat", r"sleepycat (?:license|licence|software license)", 3, 0.9),
    ("rpl-1", "reciprocal", r"reciprocal public license(?: version| v)?(?: 1(?: [015])?)?", 3, 0.92),
    ("ms-rl", "microsoft", r"microsoft reciprocal license(?: ms rl)?", 3, 0.95),
    ("ms-pl", "microsoft", r"microsoft public license(?: ms pl)?", 3, 0.95),
    ("ms-pl", "spdx", r"spdx license identifier ms pl", 4, 1.0),
    # Short permissive ones
    ("isc", "spdx", r"spdx license identifier isc", 4, 1.0),
    ("isc", "isc", r"(?:licensed|released|distributed|available) under (?:the )?isc(?: license)?", 3, 0.95),
    ("isc", "isc", r"(?:the )?isc (?:license|licence)", 2, 0.9),
    ("isc", "isc", r"license isc", 2, 0.85),
    ("isc", "permission", r"permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", 4, 0.98),
    ("isc", "permission", r"permission to use copy modify and or distribute this software for any purpose", 4, 0.96),
    ("zlib", "spdx", r"spdx license identifier zlib", 4, 1.0),
    ("zlib", "zlib", r"(?:licensed|released|distributed|available|free to use) under (?:the )?zlib(?: libpng)?(?: license)?", 3, 0.95),
    ("zlib", "zlib", r"zlib(?: libpng)? (?:license|licence)", 2, 0.9),
    ("zlib", "misrepresented", r"the origin of this software must not be misrepresented you must not claim that you wrote the original software", 4, 0.98),
    ("libpng", "libpng", r"libpng (?:license|licence)(?: version 2)?", 2, 0.88),
    ("boost-1", "spdx", r"spdx license identifier bsl 1 0", 4, 1.0),
    ("boost-1", "boost", r"boost software license(?: version| v)?(?: 1(?: 0)?)?", 3, 0.95),
    ("boost-1", "boost", r"www boost org license 1 0 txt", 3, 0.95),
    ("unlicense", "spdx", r"spdx license identifier unlicense", 4, 1.0),
    ("unlicense", "unlicense", r"(?:the )?unlicense", 2, 0.85),
    ("unlicense", "unencumbered", r"this is free and unencumbered software released into the public domain", 4, 0.99),
    ("wtfpl", "spdx", r"spdx license identifier wtfpl", 4, 1.0),
    ("wtfpl", "wtfpl", r"(?:licensed|released|distributed|available) under (?:the )?wtfpl", 3, 0.95),
    ("wtfpl", "wtfpl", r"wtfpl (?:license|licence)", 2, 0.9),
    ("wtfpl", "want", r"do what the f[a-z]{3} you want to public license", 4, 0.98),
    ("beerware", "beer", r"beer ware license(?: revision 42)?", 3, 0.95),
    ("curl", "curl", r"curl (?:license|licence)", 2, 0.8),
    ("ncsa", "spdx", r"spdx license identifier ncsa", 4, 1.0),
    ("ncsa", "illinois", r"university of illinois(?: ncsa)? open source license", 3, 0.95),
    ("artistic-1", "artistic", r"artistic license(?: version| v)? 1(?: 0)?", 3, 0.93),
    ("artistic-2", "spdx", r"spdx license identifier artistic 2 0", 4, 1.0),
    ("artistic-2", "artistic", r"artistic license(?: version| v)? 2(?: 0)?", 3, 0.93),
    ("artistic", "artistic", r"(?:the )?artistic (?:license|licence)", 1, 0.75),
    ("perl", "perl", r"under the same terms as perl itself", 3, 0.93),
    ("postgresql", "spdx", r"spdx license identifier postgresql", 4, 1.0),
    ("postgresql", "postgresql", r"(?:the )?postgresql (?:license|licence)", 3, 0.92),
    ("python-2", "spdx", r"spdx license identifier (?:psf|python) 2 0", 4, 1.0),
    ("python-2", "python", r"python software foundation license(?: agreement)?(?: version| v)?(?: 2)?", 3, 0.93),
    ("python-2", "psf", r"psf license(?: agreement)?(?: version| v)?(?: 2)?", 3, 0.92),
    ("php-3", "php", r"php license(?: version| v)?(?: 3(?: 0[01]?)?)?", 3, 0.92),
    ("ruby", "ruby", r"under the (?:same )?terms (?:of|as) (?:the )?ruby(?: s)?(?: license)?", 2, 0.85),
    ("ruby", "ruby", r"ruby (?:license|licence)", 2, 0.8),
    ("openssl", "openssl", r"openssl(?: project)? (?:license|licence)", 3, 0.9),
    ("openssl", "openssl", r"this product includes software developed by the openssl project for use in the openssl toolkit", 4, 0.97),
    ("w3c", "w3c", r"w3c software(?: notice and| and document notice and)? license", 3, 0.93),
    ("unicode", "unicode", r"unicode(?: data files and software)? license(?: agreement)?", 3, 0.9),
    ("icu", "icu", r"icu license(?: icu 1 8 1 and later)?", 3, 0.9),
    ("ofl-1", "spdx", r"spdx license identifier ofl 1 [01]", 4, 1.0),
    ("ofl-1", "font", r"sil open font license(?: version| v)?(?: 1 [01])?", 3, 0.95),
    ("ofl-1", "ofl", r"(?:licensed|released|distributed|available) under (?:the )?ofl(?: version| v)?(?: 1 [01])?", 3, 0.9),
    ("bitstream-vera", "vera", r"bitstream vera fonts? copyright", 3, 0.9),
    ("lppl-1", "latex", r"latex project public license(?: version| v)?(?: 1(?: [0-3]c?)?)?", 3, 0.95),
    ("vim", "vim", r"vim (?:license|licence)", 2, 0.85),
    ("tcl", "authors", r"the authors hereby grant permission to use copy modify distribute and license this software and its documentation", 4, 0.93),
    ("hpnd", "historical", r"historical permission notice and disclaimer", 3, 0.93),
    ("zpl-2", "zope", r"zope public license(?: zpl)?(?: version| v)?(?: 2 [01])?", 3, 0.93),
    ("upl-1", "universal", r"universal permissive license(?: version| v)?(?: 1(?: 0)?)?", 3, 0.95),
    ("ecl-2", "educational", r"educational community license(?: version| v)?(?: 2(?: 0)?)?", 3, 0.93),
    ("blueoak-1", "blue", r"blue oak model license(?: 1 0 0)?", 3, 0.95),
    ("mulan-2", "mulan", r"mulan (?:psl|permissive software license)(?: version| v)?(?: ?2)?", 3, 0.93),
    # Creative Commons and data
    ("cc0-1", "spdx", r"spdx license identifier cc0 1 0", 4, 1.0),
    ("cc0-1", "cc0", r"(?:licensed|released|distributed|available|published) under (?:the )?(?:creative commons )?cc0(?: 1 0)?(?: license)?", 3, 0.95),
    ("cc0-1", "cc0", r"(?:creative commons )?cc0(?: 1(?: 0)?)?(?: universal)? (?:license|licence|public domain dedication)", 3, 0.93),
    ("cc0-1", "publicdomain", r"creativecommons org publicdomain zero 1 0(?: license)?", 3, 0.95),
    ("cc-by", "attribution", r"creative commons attribution(?: [1-4] [05])?(?: international| unported)?(?: license| licence)?", 2, 0.9),
    ("cc-by-sa", "attribution", r"creative commons attribution share ?alike(?: [1-4] [05])?(?: international| unported)?(?: license| licence)?", 3, 0.95),
    ("cc-by-nc", "attribution", r"creative commons attribution non ?commercial(?: [1-4] [05])?(?: international| unported)?(?: license| licence)?", 3, 0.95),
    ("cc-by-nd", "attribution", r"creative commons attribution no ?deriv(?:ative)?s(?: [1-4] [05])?(?: international| unported)?(?: license| licence)?", 3, 0.95),
    ("cc-by-nc-sa", "attribution", r"creative commons attribution non ?commercial share ?alike(?: [1-4] [05])?(?: international| unported)?(?: license| licence)?", 4, 0.97),
    ("cc-by-nc-nd", "attribution", r"creative commons attribution non ?commercial no ?deriv(?:ative)?s(?: [1-4] [05])?(?: international| unported)?(?: license| licence)?", 4, 0.97),
    ("cc-by", "cc", r"(?:licensed|released|available|published|distributed) under (?:a |the )?cc by(?: [1-4] [05])?(?: license| licence)?", 2, 0.9),
    ("cc-by", "cc", r"cc by [1-4] [05]", 2, 0.88),
    ("cc-by-sa", "cc", r"cc by sa(?: [1-4] [05])?", 3, 0.93),
    ("cc-by-nd", "cc", r"cc by nd(?: [1-4] [05])?", 3, 0.93),
    ("cc-by-nc-sa", "cc", r"cc by nc sa(?: [1-4] [05])?", 4, 0.95),
    ("cc-by-nc-nd", "cc", r"cc by nc nd(?: [1-4] [05])?", 4, 0.95),
    ("cc-by", "creativecommons", r"creativecommons org licenses by(?: [1-4] [05])?", 2, 0.93),
    ("cc-by-sa", "creativecommons", r"creativecommons org licenses by sa(?: [1-4] [05])?", 3, 0.95),
    ("cc-by-nc", "creativecommons", r"creativecommons org licenses by nc(?: [1-4] [05])?", 3, 0.95),
    ("cc-by-nd", "creativecommons", r"creativecommons org licenses by nd(?: [1-4] [05])?", 3, 0.95),
    ("cc-by-nc-sa", "creativecommons", r"creativecommons org licenses by nc sa(?: [1-4] [05])?", 4, 0.96),
    ("cc-by-nc-nd", "creativecommons", r"creativecommons org licenses by nc nd(?: [1-4] [05])?", 4, 0.96),
    ("cc", "creative", r"(?:under a |under the )?creative commons (?:license|licence)", 1, 0.7),
    ("odbl-1", "spdx", r"spdx license identifier odbl 1 0", 4, 1.0),
    ("odbl-1", "database", r"open (?:data commons open )?database license(?: odbl)?(?: version| v)?(?: 1(?: 0)?)?", 3, 0.95),
    ("odbl-1", "odbl", r"(?:licensed|released|distributed|available) under (?:the )?odbl(?: version| v)?(?: 1(?: 0)?)?", 3, 0.93),
    ("odc-by-1", "commons", r"open data commons attribution license(?: version| v)?(?: 1(?: 0)?)?", 3, 0.95),
    ("pddl-1", "commons", r"open data commons public domain dedication and license(?: pddl)?", 4, 0.96),
    ("ogl-uk", "government", r"open government licence(?: version| v)?(?: [123](?: 0)?)?", 3, 0.93),
    ("cdla-permissive", "community", r"community data license agreement permissive(?: version)?(?: [12] 0)?", 3, 0.95),
    # Source-available and model licenses
    ("sspl-1", "server", r"server side public license(?: version| v)?(?: 1)?", 3, 0.95),
    ("busl-1", "business", r"business source license(?: version| v)?(?: 1 [01])?", 3, 0.95),
    ("elastic-2", "elastic", r"elastic license(?: version| v)?(?: 2(?: 0)?)?", 3, 0.92),
    ("commons-clause", "commons", r"commons clause (?:license|licence) condition(?: v1 0)?", 3, 0.95),
    ("polyform", "polyform", r"polyform (?:noncommercial|small business|shield|strict) license(?: 1 0 0)?", 3, 0.95),
    ("openrail", "rail", r"(?:bigscience |creativeml )?open ?rail(?: m| s)? license", 3, 0.92),
    # Notices that name no license
    ("public-domain", "domain", r"(?:released|dedicated|placed|put) (?:in|into|to) the public domain", 3, 0.9),
    ("public-domain", "domain", r"public domain dedication", 2, 0.8),
    ("public-domain", "domain", r"this work is in the public domain", 3, 0.9),
    ("all-rights-reserved", "reserved", r"all rights reserved", 1, 0.6),
    ("proprietary", "proprietary", r"proprietary and confidential", 2, 0.8),
    ("proprietary", "confidential", r"confidential and proprietary", 2, 0.8),
    ("proprietary", "reproduced", r"reproduced without (?:the )?(?:prior )?(?:express )?written permission", 2, 0.75),
    ("eula", "end", r"end user license agreement", 2, 0.85),
    ("no-warranty", "warranty", r"without warranty of any kind", 1, 0.4),
    ("no-warranty", "warranties", r"without warranties or conditions of any kind", 1, 0.4),
    ("copyright", "copyright", r"copyright (?:c )?(?:19|20)[0-9]{2}", 1, 0.5),
    ("unknown-license", "license", r"(?:licensed under|under the terms of) the license", 1, 0.4),
    ("unknown-license", "license", r"see (?:the )?license (?:file )?for (?:details|terms|more information)", 1, 0.4),
)


def rules() -> list[tuple[int, str, str, str, int, float, bool]]:
    """(number, label, keyword, pattern, priority, confidence, base) in order; a pattern starts at a space, ends before one.

    A keyword is looked for as a word; those that texts write together with a version (gpl3, freebsd) anywhere.
    """
    found = [(label, text.split()[0] if label == "cc-by-nc" else text.split()[-2 if label == "mit" else 0], text, 4, 1.0, True) for text, label in BASE]
    found += [(*s, False) for s in SIGNATURES]
    return [(n, label, word if word in LOOSE else f" {word} ", f" (?:{pattern})(?= )", priority, sure, base) for n, (label, word, pattern, priority, sure, base) in enumerate(found)]


# What stands in every text that the gate passes, in lower case; looked for before the gate's pattern runs.
TRIGGERS = (
    "licen", "copyright", "permission", "permitted", "warrant", "redistribut", "proprietary", "advertising", "misrepresented", "endorse", "evil", "good",
    "reserved", "domain", "cc", "creative", "invariant", "gnu", "openssl", "classpath", "mozilla", "eclipse", "terms", "remotely", "mulan", "attribution", "bsd", "expat", "under",
)


def gate() -> str:
    """Case-blind pattern that any text with a detection matches: each signature holds one of these, whatever stands between its words."""
    return rf"(?i)licen[sc]e|copyright|permission|permitted|warrant|redistribut|proprietary|advertising|misrepresented|endorse|good\P{{Alnum}}+not|rights\P{{Alnum}}+reserved|public\P{{Alnum}}+domain|cc\P{{Alnum}}+by|creativecommons|invariant\P{{Alnum}}+sections|gnu\P{{Alnum}}+(?:org|classpath)|openssl\P{{Alnum}}+project|classpath\P{{Alnum}}+exception|mozilla\P{{Alnum}}+org|eclipse\P{{Alnum}}+org|terms\P{{Alnum}}+(?:of|as)|remotely\P{{Alnum}}+through|cc0|mulan|no\P{{Alnum}}+attribution|clause\P{{Alnum}}+bsd|creative\P{{Alnum}}+commons|unlicense|expat|(?:{'|'.join(OFFERS)})\P{{Alnum}}+under|under\P{{Alnum}}+0bsd"
