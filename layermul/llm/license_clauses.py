"""Sentences that stand in the licences' own texts, as rules of the licence scan.

Each entry is written by hand: label, a keyword that stands in every match (one word, or words that
a hyphen or slash holds together, so that line breaks don't part it), and a regex over lower-cased
text in which a space stands for any white space.
"""

# Label, keyword, regex.
SENTENCES = (
    # permission notices
    ("mit", "hereby", r"permission is hereby granted, free of charge, to any person obtaining a copy"),
    ("mit", "sublicense", r"use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies"),
    ("mit", "noninfringement", r"fitness for a particular purpose and noninfringement"),
    ("mit-0", "sublicense", r"sublicense, and/or sell copies of the software, and to permit persons to whom the software is furnished to do so\.\s+the software is provided"),
    ("mit-modern", "hereby", r"permission is hereby granted, without written agreement and without license or royalty fees"),
    ("mit-advertising", "acknowledgment", r"the above copyright notice and this permission notice shall be included [^.]{1,160} acknowledgment"),
    ("x11", "advertising", r"shall not be used in advertising or otherwise to promote the sale, use or other dealings in this software"),
    ("hpnd", "suitability", r"makes? no representations about the suitability of this software for any purpose"),
    ("hpnd", "publicity", r"not be used in advertising or publicity pertaining to distribution of the software"),
    ("isc", "permission", r"permission to use, copy, modify, and/?(?:or)? ?distribute this software for any purpose"),
    ("isc", "disclaims", r"the author disclaims all warranties with regard to this software"),
    ("ntp", "permission", r"permission to use, copy, modify, and distribute this software and its documentation for any purpose with or without fee"),
    ("fsf-all-permissive", "copying", r"copying and distribution of this file, with or without modification, are permitted in any medium"),
    ("fsf-unlimited", "unlimited", r"gives unlimited permission to copy and/or distribute it"),
    ("curl", "dealings", r"the name of a copyright holder shall not be used in advertising or otherwise to promote the sale, use or other dealings"),
    # redistribution conditions
    ("bsd-1-clause", "redistributions", r"redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer"),
    ("bsd-2-clause", "redistribution", r"redistribution and use in source and binary forms, with or without modification"),
    ("bsd-2-clause", "redistributions", r"redistributions in binary form must reproduce the above copyright notice"),
    ("bsd-3-clause", "endorse", r"neither the name of [^.]{1,120} may be used to endorse or promote products"),
    ("bsd-3-clause", "endorse", r"the names? of (?:the author|its contributors|any contributors?)[^.]{0,60} may not be used to endorse or promote products"),
    ("bsd-3-clause-clear", "patent", r"no express or implied licenses to any party's patent rights are granted by this license"),
    ("bsd-3-clause-lbnl", "upgrades", r"under no obligation whatsoever to provide any bug fixes, patches, or upgrades to the features, functionality or performance"),
    ("bsd-3-clause-no-nuclear", "nuclear", r"not designed, licensed or intended for use in the design, construction, operation or maintenance of any nuclear facility"),
    ("bsd-4-clause", "advertising", r"all advertising materials mentioning features or use of this software"),
    ("bsd-patent", "grants", r"each copyright holder and contributor hereby grants to those receiving rights under this license a perpetual, worldwide"),
    ("bsd-source-code", "attribution", r"redistributions of source code must retain [^.]{1,200} redistributions? [^.]{0,80} attribution"),
    ("beerware", "beer", r"you can buy me a beer in return"),
    ("ncsa", "restriction", r"(?:deal|dealing) with the software without restriction"),
    ("zlib", "'as-is'", r"this software is provided 'as-is', without any express or implied warranty"),
    ("zlib", "misrepresented", r"the origin of this software must not be misrepresented"),
    ("zlib", "misrepresented", r"altered source versions must be plainly marked as such, and must not be misrepresented"),
    ("libpng", "reference", r"the png reference library is supplied \"as is\""),
    ("openssl", "toolkit", r"this product includes software developed by the openssl project for use in the openssl toolkit"),
    ("ssleay", "cryptographic", r"this product includes cryptographic software written by"),
    ("apache-1.1", "acknowledgment", r"the end-user documentation included with the redistribution, if any, must include the following acknowledgment"),
    ("info-zip", "self-extracting", r"redistribution of a standard (?:unzipsfx )?binary [^.]{0,80}self-extracting archive"),
    ("imagemagick", "imagemagick", r"to use imagemagick in packages or distributions that you create"),
    ("ftl", "freetype", r"portions of this software are copyright [^.]{1,60} the freetype project"),
    ("ijg", "jpeg", r"this software is based in part on the work of the independent jpeg group"),
    ("tcl", "verbatim", r"provided that existing copyright notices are retained in all copies and that this notice is included verbatim"),
    ("unicode", "unicode", r"unicode data files and software [^.]{0,80}without restriction"),
    ("icu", "icu", r"icu license - icu [0-9.]+ and later"),
    ("vim", "vim", r"there are no restrictions on distributing unmodified copies of vim"),
    ("php-3.01", "php", r"this product includes php software, freely available from"),
    ("python-2.0", "licensee", r"grants licensee a nonexclusive, royalty-free, world-?wide license to reproduce, analyze, test"),
    ("ruby", "verbatim", r"you may make and give away verbatim copies of the source form of the software without restriction"),
    ("postgresql", "consequential", r"liable to any party for direct, indirect, special, incidental, or consequential damages, including lost profits, arising out of the use of this software and its documentation"),
    ("w3c", "viewable", r"the full text of this notice in a location viewable to users of the redistributed or derivative work"),
    ("wtfpl", "fuck", r"do what the fuck you want to public license"),
    ("wtfpl", "fuck", r"you just do what the fuck you want to"),
    ("bsl-1.0", "boost", r"distributed under the boost software license"),
    ("bsl-1.0", "machine-executable", r"solely in the form of machine-executable object code generated by a source language processor"),
    ("json", "evil", r"the software shall be used for good, not evil"),
    ("blueoak-1.0.0", "contributor", r"no contributor can revoke this license"),
    ("upl-1.0", "lrgrwrks.txt", r"lrgrwrks\.txt file if one is included with the software"),
    # dedications
    ("unlicense", "unencumbered", r"free and unencumbered software released into the public domain"),
    ("unlicense", "dedicate", r"dedicate any and all copyright interest in the software to the public domain"),
    ("cc0", "waives", r"affirmer hereby overtly, fully, permanently, irrevocably and unconditionally waives"),
    ("cc0", "dedicated", r"has dedicated the work to the public domain by waiving all of his or her rights"),
    ("public-domain", "domain", r"(?:placed|released|dedicated) (?:in|into|to) the public domain"),
    ("public-domain", "domain", r"(?:this|the) (?:work|file|code|text|software) is (?:hereby )?(?:in|part of) the public domain"),
    ("public-domain-us", "government", r"work of the (?:u\.s\.|united states) government and is (?:therefore )?not subject to copyright"),
    ("pddl", "dedication", r"public domain dedication and licen[cs]e"),
    # copyleft notices
    ("gpl", "redistribute", r"this program is free software[:;] you can redistribute it"),
    ("gpl", "received", r"you should have received a copy of the gnu general public license along with this program"),
    ("gpl", "merchantability", r"without even the implied warranty of merchantability or fitness for a particular purpose\. see the gnu general public license"),
    ("gpl-2.0", "franklin", r"51 franklin st(?:reet)?, fifth floor, boston, ma"),
    ("gpl-2.0-or-later", "option", r"either version 2 of the license,? or \(at your option\) any later version"),
    ("gpl-2.0", "prominent", r"you must cause the modified files to carry prominent notices stating that you changed the files and the date of any change"),
    ("gpl-3.0-or-later", "option", r"either version 3 of the license,? or \(at your option\) any later version"),
    ("gpl-3.0", "tivo", r"tivoization"),
    ("gpl-3.0", "convey", r"to \"convey\" a work means any kind of propagation that enables other parties to make or receive copies"),
    ("gpl-3.0", "installation", r"\"installation information\" for a user product means any methods"),
    ("gpl-classpath", "linking", r"linking this library statically or dynamically with other modules is making a combined work"),
    ("gpl-font", "embed", r"if you create a document which uses this font, and embed this font"),
    ("gpl-bison", "skeleton", r"you may create a larger work that contains part or all of the bison parser skeleton"),
    ("gcc-runtime", "runtime", r"additional permissions described in the gcc runtime library exception"),
    ("lgpl", "redistribute", r"this library is free software[:;] you can redistribute it"),
    ("lgpl-2.1-or-later", "option", r"either version 2\.1 of the license,? or \(at your option\) any later version"),
    ("lgpl-2.1", "library", r"a \"work that uses the library\""),
    ("lgpl-3.0", "supplemented", r"supplemented by the additional permissions listed below"),
    ("agpl-3.0", "remotely", r"prominently offer all users interacting with it remotely through a computer network"),
    ("gfdl", "invariant", r"with no invariant sections, no front-cover texts,? and no back-cover texts"),
    ("mpl-1.1", "initial", r"the initial developer of the original code is"),
    ("mpl-1.1", "mozilla", r"the contents of this file are subject to the mozilla public license"),
    ("mpl-2.0", "mozilla", r"this source code form is subject to the terms of the mozilla public license"),
    ("mpl-2.0", "incompatible", r"this source code form is \"incompatible with secondary licenses\""),
    ("npl-1.1", "netscape", r"subject to the netscape public license"),
    ("cddl-1.0", "development", r"subject to the terms of the common development and distribution license"),
    ("epl-2.0", "accompanying", r"this program and the accompanying materials are made available under the terms of the eclipse public license"),
    ("cpl-1.0", "recipient", r"any use, reproduction or distribution of the program constitutes recipient's acceptance of this agreement"),
    ("apsl-2.0", "apple", r"this file contains original code and/or modifications of original code as defined in and that are subject to the apple public source license"),
    ("osl-3.0", "licensed", r"licensed under the open software license version 3\.0"),
    ("afl-3.0", "academic", r"licensed under the academic free license version [23]\.[01]"),
    ("ms-pl", "microsoft", r"microsoft (?:public|reciprocal) license \(ms-[pr]l\)"),
    ("qpl-1.0", "public", r"the q public license"),
    ("artistic-1.0", "semblance", r"maintains some semblance of artistic control over the development of the package"),
    ("artistic-2.0", "standard", r"you are permitted to use the standard version and create and use modified versions for any purpose"),
    ("eupl-1.2", "eupl", r"licensed under the eupl"),
    ("cecill-2.1", "cecill", r"governed by the cecill(?:-[bc])? license under french law"),
    ("sleepycat", "accompanied", r"redistributions in any form must be accompanied by information on how to obtain complete source code"),
    ("odbl-1.0", "database", r"made available under the open database license"),
    ("ofl-1.1", "font", r"this font software is licensed under the sil open font license"),
    ("lppl-1.3c", "latex", r"distributed and/or modified under the conditions of the latex project public license"),
    # permissive notices with patents
    ("apache-2.0", "compliance", r"you may not use this file except in compliance with the license"),
    ("apache-2.0", "apache.org", r"(?:http|https)://(?:www\.)?apache\.org/licenses/license-2\.0"),
    ("apache-2.0", "conditions", r"without warranties or conditions of any kind, either express or implied"),
    ("apache-2.0", "cross-claim", r"patent litigation against any entity \(including a cross-claim or counterclaim in a lawsuit\)"),
    ("apache-2.0", "contributor", r"under one or more contributor license agreements"),
    ("ecl-2.0", "educational", r"licensed under the educational community license"),
    # creative works
    ("cc", "creativecommons.org", r"creativecommons\.org/licenses/(?:by|sa|nc|nd)[a-z-]*/[1-4]\.[05]"),
    ("cc0", "creativecommons.org", r"creativecommons\.org/publicdomain/zero/1\.0"),
    ("public-domain-mark", "creativecommons.org", r"creativecommons\.org/publicdomain/mark/1\.0"),
    ("cc-by", "appropriate", r"you must give appropriate credit, provide a link to the license, and indicate if changes were made"),
    ("cc-by-sa", "remix", r"if you remix, transform, or build upon the material, you must distribute your contributions under the same license"),
    ("cc-by-nc", "commercial", r"you may not use the material for commercial purposes"),
    ("cc-by-nd", "remix", r"if you remix, transform, or build upon the material, you may not distribute the modified material"),
    ("ogl", "government", r"contains public sector information licensed under the open government licence"),
    # restricted
    ("proprietary", "proprietary", r"proprietary and confidential"),
    ("proprietary", "unauthorized", r"unauthorized copying of this file, via any medium,? is strictly prohibited"),
    ("proprietary", "written", r"(?:reproduced|distributed|transmitted)[^.]{0,160} without the prior written (?:permission|consent)"),
    ("eula", "end-user", r"end-user licen[cs]e agreement"),
    ("evaluation", "evaluation", r"for (?:internal )?evaluation purposes only"),
    ("non-commercial", "non-commercial", r"for (?:personal and )?non-commercial (?:use|purposes) only"),
    ("busl-1.1", "business", r"business source license"),
    ("sspl", "server", r"server side public license"),
    ("elastic-2.0", "managed", r"provide the software to third parties as a hosted or managed service"),
    ("commons-clause", "commons", r"commons clause[\"”]? license condition"),
    ("copyright", "copyright", r"copyright (?:\(c\)|©)? ?(?:19|20)[0-9]{2}"),
)
