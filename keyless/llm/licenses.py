"""License and copyright detection by ordered signature rules, in DataFrame expressions only.

A text is reduced to its words (ASCII case folded) with one blank before and after each.  Its words are met with the keywords of
all rules once; where some are found, the rules that have one of them are matched.  Detections are
intervals of words.  In the order of their starts, longer ones first, a detection inside an earlier kept one goes unless its rule
has a higher priority (a smaller number).  The three base phrases are counted apart and always give their labels.

Defined cases: null or empty text has no words, no labels and score 0; rows are independent; clashing names are kept apart.
"""

from __future__ import annotations

import functools

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from keyless.llm.workspace import table

SEPARATOR = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
BASE = [("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved")]

#: Rules by hand: (label, priority, keywords, expression over words); one of the keywords is a word of whatever the expression matches.  Priorities: 1 an exact identifier or a versioned name, 2 the
#: name of a license, 3 a sentence of its text, 4 a notice, 5 a hint.
BY_HAND = [
    ("mit", 2, "mit", "(?:the )?mit (?:x11 )?licen[sc]e"),
    ("mit", 2, "mit", "licen[sc]ed under (?:the )?mit"),
    ("mit", 3, "permission", "permission is hereby granted free of charge to any person obtaining a copy of this software(?: and associated documentation files)?"),
    ("mit", 3, "merchantability", "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability"),
    ("mit-0", 1, "mit", "mit 0|mit no attribution(?: licen[sc]e)?"),
    ("x11", 2, "x11", "x11 licen[sc]e"),
    ("isc", 2, "isc", "(?:the )?isc licen[sc]e"),
    ("isc", 3, "permission", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    ("bsd", 2, "bsd", "(?:the )?(?:new |modified |simplified |revised )?bsd licen[sc]e"),
    ("bsd", 2, "bsd", "bsd style licen[sc]e"),
    ("bsd", 3, "redistribution", "redistribution and use in source and binary forms with or without modification are permitted"),
    ("bsd-3-clause", 3, "endorse", "neither the name of (?:\\S+ ){1,12}?nor the names of its contributors may be used to endorse or promote products"),
    ("bsd-4-clause", 3, "advertising", "all advertising materials mentioning features or use of this software must display the following acknowledg(?:e)?ment"),
    ("0bsd", 1, "0bsd|bsd", "0bsd|bsd zero clause(?: licen[sc]e)?"),
    ("apache", 2, "apache", "(?:the )?apache (?:software )?licen[sc]e"),
    ("apache-2.0", 3, "apache", "you may not use this file except in compliance with the licen[sc]e you may obtain a copy of the licen[sc]e at http(?:s)? www apache org licenses licen[sc]e 2 0"),
    ("apache-2.0", 3, "compliance", "you may not use this file except in compliance with the licen[sc]e"),
    ("gpl", 2, "gnu", "(?:the )?gnu (?:general public licen[sc]e|gpl)"),
    ("gpl", 2, "gpl", "gpl licen[sc]ed?"),
    ("gpl", 3, "redistribute", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public licen[sc]e"),
    ("gpl", 3, "warranty", "this program is distributed in the hope that it will be useful but without any warranty"),
    ("gpl-exception", 2, "exception", "gpl (?:linking|classpath|font|bison) exception|(?:gcc runtime library|classpath|linking) exception"),
    ("lgpl", 2, "lesser", "(?:the )?(?:gnu )?lesser general public licen[sc]e"),
    ("lgpl", 2, "library", "(?:the )?(?:gnu )?library general public licen[sc]e"),
    ("agpl", 2, "affero", "(?:the )?(?:gnu )?affero general public licen[sc]e"),
    ("gfdl", 2, "documentation", "(?:the )?(?:gnu )?free documentation licen[sc]e"),
    ("mpl", 2, "mozilla", "(?:the )?mozilla public licen[sc]e"),
    ("mpl", 3, "mozilla", "this source code form is subject to the terms of the mozilla public licen[sc]e"),
    ("epl", 2, "eclipse", "(?:the )?eclipse (?:public|distribution) licen[sc]e"),
    ("cddl", 2, "common", "(?:the )?common development and distribution licen[sc]e"),
    ("cpl", 2, "common", "(?:the )?common public licen[sc]e"),
    ("ibm-pl", 2, "ibm", "ibm public licen[sc]e"),
    ("eupl", 2, "european", "(?:the )?european union public licen[sc]e"),
    ("cecill", 2, "cecill", "cecill(?: [bc])?(?: licen[sc]e)?"),
    ("artistic", 2, "artistic", "(?:the )?(?:clarified )?artistic licen[sc]e"),
    ("perl", 3, "perl", "under the same terms as perl itself"),
    ("zlib", 2, "zlib", "(?:the )?zlib(?: libpng)? licen[sc]e"),
    ("zlib", 3, "altered", "altered source versions must be plainly marked as such and must not be misrepresented as being the original software"),
    ("libpng", 2, "libpng", "libpng licen[sc]e"),
    ("boost", 2, "boost", "(?:the )?boost software licen[sc]e"),
    ("unlicense", 2, "unlicense", "(?:the )?unlicense"),
    ("unlicense", 3, "unencumbered", "this is free and unencumbered software released into the public domain"),
    ("wtfpl", 2, "want", "do what the f\\S* you want to public licen[sc]e"),
    ("wtfpl", 1, "wtfpl", "wtfpl"),
    ("beerware", 2, "beer|beerware", "(?:the )?beer ?ware licen[sc]e"),
    ("psf", 2, "python|psf", "(?:the )?python software foundation licen[sc]e|(?:the )?psf licen[sc]e"),
    ("php", 2, "php", "(?:the )?php licen[sc]e"),
    ("ruby", 2, "ruby", "ruby licen[sc]e|under the same terms as ruby"),
    ("openssl", 2, "openssl", "openssl licen[sc]e"),
    ("openssl", 3, "openssl", "this product includes software developed by the openssl project"),
    ("ofl", 2, "font", "(?:the )?(?:sil )?open font licen[sc]e"),
    ("ms-pl", 2, "microsoft", "microsoft (?:public|reciprocal) licen[sc]e"),
    ("osl", 2, "software", "open software licen[sc]e"),
    ("afl", 2, "academic", "academic free licen[sc]e"),
    ("upl", 2, "universal", "universal permissive licen[sc]e"),
    ("ncsa", 2, "ncsa", "(?:university of illinois )?ncsa open source licen[sc]e"),
    ("postgresql", 2, "postgresql", "postgresql licen[sc]e"),
    ("w3c", 2, "w3c", "w3c (?:software )?(?:notice and )?(?:document )?licen[sc]e"),
    ("icu", 2, "icu", "icu licen[sc]e"),
    ("unicode", 2, "unicode", "unicode (?:terms of use|licen[sc]e agreement|inc licen[sc]e)"),
    ("cc0", 2, "cc0", "cc0(?: 1 0)?(?: universal)?"),
    ("cc0", 2, "zero", "creative commons zero"),
    ("cc", 2, "creative", "creative commons(?: licen[sc]e)?"),
    ("cc", 5, "creativecommons", "creativecommons org licenses"),
    ("public-domain", 4, "domain", "(?:released |placed |dedicated )?(?:in|into|to) the public domain"),
    ("public-domain", 5, "domain", "public domain"),
    ("odbl", 2, "database", "open (?:data commons )?(?:open )?database licen[sc]e"),
    ("odc-by", 2, "commons", "open data commons attribution licen[sc]e"),
    ("pddl", 2, "domain", "public domain dedication and licen[sc]e"),
    ("elastic", 2, "elastic", "elastic licen[sc]e"),
    ("sspl", 2, "server", "server side public licen[sc]e"),
    ("busl", 2, "business", "business source licen[sc]e"),
    ("commons-clause", 2, "clause", "commons clause"),
    ("proprietary", 3, "proprietary", "(?:this (?:software|document) is )?(?:confidential and )?proprietary(?: and confidential)?"),
    ("proprietary", 3, "unauthorized|unauthorised", "unauthori[sz]ed (?:copying|reproduction|distribution|use)(?: \\S+){0,8}? (?:is )?(?:strictly )?prohibited"),
    ("reserved", 4, "reserved", "all rights reserved"),
    ("reserved", 5, "reserved", "some rights reserved|no rights reserved"),
    ("copyright", 4, "copyright", "copyright (?:c )?(?:19|20)\\d\\d(?: (?:19|20)\\d\\d)*"),
    ("copyright", 5, "copyright", "copyright(?: c)?"),
    ("licensed", 5, "licensed", "licensed (?:under|to)(?: the)?"),
    ("licensed", 5, "see", "see (?:the )?(?:accompanying )?(?:file )?(?:licen[sc]e|copying)(?: file)?(?: for (?:more )?details)?"),
    ("trademark", 5, "trademark|trademarks", "(?:registered )?trademarks?(?: of)?"),
    ("no-warranty", 4, "without", "without warrant(?:y|ies)(?: or conditions)? of any kind"),
    ("no-warranty", 4, "liable", "in no event shall (?:\\S+ ){1,12}?be liable"),
    ("non-commercial", 4, "commercial|noncommercial", "for non ?commercial (?:use|purposes?)(?: only)?"),
    ("patent", 4, "patent", "patent (?:licen[sc]e|grant)"),
    ("attribution", 5, "attribution", "attribution (?:is )?required"),
    ("bsd", 3, "contributors", "this software is provided by the (?:copyright holders?|regents|authors?) and contributors as is"),
    ("bsd", 3, "redistributions", "redistributions (?:of source code|in binary form) must (?:retain|reproduce) the above copyright notice"),
    ("isc", 3, "disclaims", "the author disclaims all warranties with regard to this software"),
    ("apache-2.0", 3, "basis", "distributed on an as is basis without warranties or conditions of any kind"),
    ("epl", 3, "accompanying", "this program and the accompanying materials are made available under the terms of the eclipse"),
    ("lgpl", 3, "library", "this library is free software you can redistribute it and or modify it under the terms of the gnu (?:lesser|library) general public licen[sc]e"),
    ("agpl", 3, "affero", "under the terms of the gnu affero general public licen[sc]e"),
    ("gpl", 3, "gnu", "you should have received a copy of the gnu (?:lesser |library |affero )?general public licen[sc]e"),
    ("gfdl", 3, "invariant", "with no invariant sections no front cover texts and no back cover texts"),
    ("mpl", 3, "mpl", "if a copy of the mpl was not distributed with this file"),
    ("mpl", 2, "mpl", "licen[sc]ed under (?:the )?mpl"),
    ("cc0", 3, "waived", "waived all copyright and related (?:or|and) neighbou?ring rights"),
    ("cc", 3, "creative", "this work is licen[sc]ed under a creative commons"),
    ("boost", 3, "boost", "distributed under the boost software licen[sc]e"),
    ("ofl", 3, "font", "reserved font names?"),
    ("unlicense", 3, "dedication", "we make this dedication for the benefit of the public at large"),
    ("hpnd", 2, "historical", "historical permission notice and disclaimer"),
    ("hpnd", 3, "supporting", "both that copyright notice and this permission notice appear in supporting documentation"),
    ("json", 2, "json", "json licen[sc]e"),
    ("json", 3, "evil", "the software shall be used for good not evil"),
    ("ms-rl", 2, "reciprocal", "microsoft reciprocal licen[sc]e"),
    ("adobe", 2, "adobe", "adobe (?:glyph list |systems |source code )?licen[sc]e(?: agreement)?"),
    ("aladdin", 2, "aladdin", "aladdin free public licen[sc]e"),
    ("amazon", 2, "amazon", "amazon software licen[sc]e"),
    ("apsl", 2, "apple", "apple public source licen[sc]e"),
    ("apple-sample", 2, "apple", "apple (?:mit|sample code) licen[sc]e"),
    ("bittorrent", 2, "bittorrent", "bittorrent open source licen[sc]e"),
    ("blueoak", 2, "oak", "blue oak model licen[sc]e"),
    ("bsd-patent", 1, "patent", "bsd (?:2 clause )?plus patent(?: licen[sc]e)?"),
    ("bzip2", 2, "bzip2", "bzip2(?: and libbzip2)? licen[sc]e"),
    ("catosl", 2, "trusted", "computer associates trusted open source licen[sc]e"),
    ("cdla", 2, "community", "community data licen[sc]e agreement(?: (?:permissive|sharing))?"),
    ("cnri", 2, "cnri", "cnri (?:open source )?(?:gpl compatible )?licen[sc]e(?: agreement)?"),
    ("condor", 2, "condor", "condor public licen[sc]e"),
    ("copyleft-next", 2, "copyleft", "copyleft next"),
    ("cpal", 2, "attribution", "common public attribution licen[sc]e"),
    ("cuda", 2, "computational", "computational use of data agreement"),
    ("curl", 2, "curl", "curl licen[sc]e"),
    ("dfsl", 2, "german|lizenz", "german free software licen[sc]e|deutsche freie software lizenz"),
    ("dual", 4, "dual|dually", "(?:dual|dually) licen[sc]ed(?: under)?"),
    ("ecl", 2, "educational", "educational community licen[sc]e"),
    ("efl", 2, "eiffel", "eiffel forum licen[sc]e"),
    ("entessa", 2, "entessa", "entessa public licen[sc]e"),
    ("eula", 4, "eula|agreement", "end user licen[sc]e agreement(?: eula)?|eula"),
    ("fair", 2, "fair", "fair (?:source )?licen[sc]e"),
    ("frameworx", 2, "frameworx", "frameworx open licen[sc]e"),
    ("freebsd-doc", 2, "freebsd", "freebsd documentation licen[sc]e"),
    ("freeimage", 2, "freeimage", "freeimage public licen[sc]e"),
    ("freetype", 2, "freetype", "(?:the )?freetype (?:project )?licen[sc]e"),
    ("functional-source", 2, "functional", "functional source licen[sc]e"),
    ("gemma", 2, "gemma", "gemma terms of use"),
    ("gust", 2, "gust", "gust font (?:nosource )?licen[sc]e"),
    ("hippocratic", 2, "hippocratic", "hippocratic licen[sc]e"),
    ("ijg", 2, "jpeg", "independent jpeg group(?: licen[sc]e)?"),
    ("imagemagick", 2, "imagemagick", "imagemagick licen[sc]e"),
    ("info-zip", 2, "zip", "info zip licen[sc]e"),
    ("intel", 2, "intel", "intel (?:open source|simplified software) licen[sc]e"),
    ("ipa", 2, "ipa", "ipa font licen[sc]e"),
    ("jasper", 2, "jasper", "jasper licen[sc]e"),
    ("lal", 2, "libre|art", "licen[sc]e art libre|free art licen[sc]e"),
    ("leptonica", 2, "leptonica", "leptonica licen[sc]e"),
    ("llama", 2, "llama", "llama(?: \\d){0,2} community licen[sc]e(?: agreement)?"),
    ("lppl", 2, "latex", "(?:the )?latex project public licen[sc]e"),
    ("lucent", 2, "lucent", "lucent public licen[sc]e"),
    ("miros", 2, "miros", "miros licen[sc]e"),
    ("motosoto", 2, "motosoto", "motosoto open source licen[sc]e"),
    ("mulan", 2, "mulan", "mulan (?:permissive software|public) licen[sc]e"),
    ("nasa", 2, "nasa", "nasa open source agreement"),
    ("naumen", 2, "naumen", "naumen public licen[sc]e"),
    ("net-snmp", 2, "snmp", "net snmp licen[sc]e"),
    ("nethack", 2, "nethack", "nethack general public licen[sc]e"),
    ("nmap", 2, "nmap", "nmap public source licen[sc]e"),
    ("nokia", 2, "nokia", "nokia open source licen[sc]e"),
    ("npl", 2, "netscape", "netscape public licen[sc]e"),
    ("oclc", 2, "oclc", "oclc research public licen[sc]e"),
    ("ogl", 2, "government", "open government licen[sc]e"),
    ("oldap", 2, "openldap", "(?:the )?openldap public licen[sc]e"),
    ("openrail", 2, "rail|openrail", "(?:creativeml )?(?:open rail|openrail)(?: m)?(?: licen[sc]e)?"),
    ("parity", 2, "parity", "parity public licen[sc]e"),
    ("polyform", 2, "polyform", "polyform (?:noncommercial|small business|internal use|perimeter|shield|strict|free trial)(?: licen[sc]e)?"),
    ("prosperity", 2, "prosperity", "prosperity public licen[sc]e"),
    ("qhull", 2, "qhull", "qhull (?:licen[sc]e|copyright)"),
    ("qpl", 2, "q", "q public licen[sc]e"),
    ("rpl", 2, "reciprocal", "reciprocal public licen[sc]e"),
    ("rpsl", 2, "realnetworks", "realnetworks public source licen[sc]e"),
    ("sendmail", 2, "sendmail", "sendmail licen[sc]e"),
    ("sgi-b", 2, "sgi", "sgi free software licen[sc]e(?: b)?"),
    ("sissl", 2, "sun", "sun industry standards source licen[sc]e"),
    ("sleepycat", 2, "sleepycat", "sleepycat licen[sc]e"),
    ("sun", 2, "sun", "sun (?:public|microsystems inc binary code|binary code) licen[sc]e(?: agreement)?"),
    ("tcl", 2, "tcl", "tcl tk licen[sc]e"),
    ("ubuntu-font", 2, "ubuntu", "ubuntu font licen[sc]e"),
    ("vim", 2, "vim", "vim licen[sc]e"),
    ("vsl", 2, "vovida", "vovida software licen[sc]e"),
    ("watcom", 2, "watcom", "sybase open watcom public licen[sc]e"),
    ("xfree86", 2, "xfree86", "xfree86 licen[sc]e"),
    ("zend", 2, "zend", "zend (?:engine )?licen[sc]e"),
    ("zimbra", 2, "zimbra", "zimbra public licen[sc]e"),
    ("zpl", 2, "zope", "zope public licen[sc]e"),
    ("crown", 4, "crown", "crown copyright"),
    ("patent", 4, "royalty", "worldwide non exclusive no charge royalty free(?: irrevocable)? (?:copyright|patent) licen[sc]e"),
    ("no-warranty", 4, "merchantability", "warrant(?:y|ies) of merchantability(?: (?:and|or) fitness for a particular purpose)?"),
    ("no-copying", 4, "copied|reproduced|redistributed", "may not be (?:copied|reproduced|redistributed)(?: \\S+){0,6}? without (?:the )?(?:prior |express )?(?:written )?permission"),
    ("restricted-use", 5, "personal|educational|research|evaluation", "for (?:personal|educational|research|evaluation) (?:use|purposes) only"),
]


@functools.lru_cache(maxsize=1)
def rules() -> list[tuple[str, int, str, str]]:
    """The rules by hand, and those that follow from them by version, form and part, in order of priority."""
    out = [(label, rank, key, body) for label, rank, key, body in BY_HAND]
    families = {
        "gpl": ("general public", "gpl", ("1 0", "2 0", "3 0")), "lgpl": ("lesser general public", "lgpl", ("2 0", "2 1", "3 0")), "agpl": ("affero general public", "agpl", ("1 0", "3 0")),
        "gfdl": ("free documentation", "gfdl", ("1 1", "1 2", "1 3")), "mpl": ("mozilla public", "mpl", ("1 0", "1 1", "2 0")), "epl": ("eclipse public", "epl", ("1 0", "2 0")),
        "apache": ("apache", "apache", ("1 0", "1 1", "2 0")), "eupl": ("european union public", "eupl", ("1 0", "1 1", "1 2")), "artistic": ("artistic", "artistic", ("1 0", "2 0")),
        "cddl": ("common development and distribution", "cddl", ("1 0", "1 1")), "osl": ("open software", "osl", ("1 0", "2 0", "2 1", "3 0")), "afl": ("academic free", "afl", ("1 2", "2 0", "2 1", "3 0")),
        "cecill": ("cecill", "cecill", ("1 0", "1 1", "2 0", "2 1")), "php": ("php", "php", ("3 0", "3 01")), "ofl": ("open font", "ofl", ("1 0", "1 1")), "boost": ("boost software", "bsl", ("1 0",)),
        "zpl": ("zope public", "zpl", ("1 1", "2 0", "2 1")), "lppl": ("latex project public", "lppl", ("1 0", "1 1", "1 2", "1 3")), "apsl": ("apple public source", "apsl", ("1 0", "1 1", "1 2", "2 0")),
        "npl": ("netscape public", "npl", ("1 0", "1 1")), "qpl": ("q public", "qpl", ("1 0",)), "rpl": ("reciprocal public", "rpl", ("1 1", "1 5")), "elastic": ("elastic", "elastic", ("1 0", "2 0")),
    }
    for label, (long, short, versions) in families.items():
        for v in versions:
            number = v.replace(" ", ".")
            # "3 0" is also written "3"
            loose = v.removesuffix(" 0") + "(?: 0)?" if v.endswith(" 0") else v
            out.append((f"{label}-{number}", 1, long.split(" ")[0], f"(?:the )?(?:gnu )?{long} licen[sc]e(?: as published by the free software foundation either)? (?:version |v )?v?{loose}(?: (?:or|and) (?:any |\\(at your option\\) )?later(?: versions?)?)?"))
            out.append((f"{label}-{number}", 1, f"{short}|{short}{v[0]}|{short}v{v[0]}", f"{short} ?v?{loose}(?: (?:only|or later))?"))
    names = {"": "", "sa": "share ?alike", "nc": "non ?commercial", "nd": "no deriv(?:ative)?s?(?: works)?"}
    for parts in (("sa",), ("nc",), ("nd",), ("nc", "sa"), ("nc", "nd"), ()):
        label = "-".join(("cc-by", *parts))
        out.append((label, 2, "cc", " ".join(("cc by", *parts))))
        out.append((label, 2, "creative", " ".join(("creative commons attribution", *(names[p] for p in parts)))))
        out.append((label, 2, "creativecommons", " ".join(("creativecommons org licenses by", *parts))))
        for v in ("1 0", "2 0", "2 5", "3 0", "4 0"):
            number = v.replace(" ", ".")
            out.append((f"{label}-{number}", 1, "cc", " ".join(("cc by", *parts, v))))
            out.append((f"{label}-{number}", 1, "creative", " ".join(("creative commons attribution", *(names[p] for p in parts), f"(?:licen[sc]e )?{v}(?: (?:international|unported|generic))?"))))
            out.append((f"{label}-{number}", 1, "creativecommons", " ".join(("creativecommons org licenses by", *parts, v))))
    for n, word in ((2, "two"), (3, "three"), (4, "four")):
        out.append((f"bsd-{n}-clause", 1, "clause", f"(?:the )?(?:bsd (?:{n}|{word}) clause|(?:{n}|{word}) clause bsd)(?: licen[sc]e)?"))
    known = sorted({label for label, *_ in out if label not in ("copyright", "licensed", "reserved", "no-warranty")})
    for label in known:
        out.append((label, 1, "spdx", "spdx licen[sc]e identifier " + label.replace("-", " ").replace(".", " ")))
    return sorted(out, key=lambda r: r[1])


def _positions(norm: Column, expression: Column) -> Column:
    """Word numbers at which the expression, words with a blank before, matches."""
    marked = F.split(F.substring(F.regexp_replace(norm, expression, F.lit("\x01$0")), 1, 1 << 30), " ")
    # a match begins at the blank before its first word, so the mark ends the word before
    return F.filter(F.transform(marked, lambda w, i: F.when(w.endswith("\x01"), i.cast("long"))), lambda i: i.isNotNull())


def scan(docs: DataFrame, text: str = "text") -> DataFrame:
    """(n_words, n_base, first_word, last_word, base_labels, labels, score, detections) after the columns of ``docs``."""
    own = ["n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "detections"]
    table_ = [(label, rank, order, key.split("|"), f" (?:{body})(?= )") for order, (label, rank, key, body) in enumerate(rules())]
    known = sorted({k for *_, keys, _ in table_ for k in keys} | {p.split(" ")[0] for p, _ in BASE})
    row = [c for c in docs.columns if c.lower() not in own]
    words = F.trim(F.regexp_replace(F.coalesce(F.col(text), F.lit("")), SEPARATOR, " "))
    first = docs.select(F.struct(*row).alias("row"), words.alias("plain"))
    blanks = lambda c: (F.length(c) - F.length(F.replace(c, F.lit(" "), F.lit("")))).cast("long")
    first = first.withColumn("n_words", F.when(F.length("plain") == 0, F.lit(0).cast("long")).otherwise(blanks(F.col("plain")) + 1))
    folded = F.translate(F.concat(F.lit(" "), F.col("plain"), F.lit(" ")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    # Unicode folding finds at least what ASCII folding does
    have = F.array_intersect(F.split(F.lower("plain"), " ", -1), F.array(*map(F.lit, known)))
    first = first.withColumn("have", have)
    first = first.select("row", "n_words", F.when(F.size("have") > 0, F.col("have")).alias("have"), F.when(F.size("have") > 0, folded).alias("norm"))
    norm = F.col("norm")
    kind = "array<struct<label:string,priority:int,rule:int,keys:array<string>,body:string>>"
    literal = F.from_json(F.lit(_json(table_)), kind)
    hits = F.filter(literal, lambda r: F.arrays_overlap(r["keys"], F.col("have")) & F.regexp_like(norm, r["body"]))
    second = first.withColumn("hits", F.when(norm.isNotNull(), hits))

    def found(r: Column) -> Column:
        spans = F.arrays_zip(_positions(norm, r["body"]).alias("start"), F.transform(F.regexp_extract_all(norm, r["body"], F.lit(0)), lambda h: blanks(h)).alias("n"))
        return F.transform(spans, lambda s: F.struct(s["start"].alias("start"), (-s["n"]).alias("minus"), r["priority"].alias("priority"), r["rule"].alias("rule"), r["label"].alias("label")))

    third = second.withColumn("found", F.array_sort(F.flatten(F.transform("hits", found))))
    each = "array<struct<start:bigint,minus:bigint,priority:int,rule:int,label:string>>"
    state = F.struct(F.array().cast(each).alias("kept"), F.lit(-1).cast("bigint").alias("end"), F.lit(0).alias("priority"), F.lit(0).cast("bigint").alias("covered"))

    def step(s: Column, d: Column) -> Column:
        end = d["start"] - d["minus"]
        inside = end <= s["end"]
        take = ~inside | (d["priority"] < s["priority"])
        return F.struct(
            F.when(take, F.array_append(s["kept"], d)).otherwise(s["kept"]).alias("kept"),
            F.greatest(end, s["end"]).alias("end"),
            F.when(inside, s["priority"]).otherwise(d["priority"]).alias("priority"),
            (s["covered"] + F.greatest(F.lit(0).cast("bigint"), end - F.greatest(s["end"], d["start"]))).alias("covered"),
        )

    def based(phrase: str, label: str) -> Column:
        return F.transform(_positions(norm, F.lit(f" {phrase}(?= )")), lambda i: F.struct(i.alias("at"), F.lit(label).alias("label")))

    places = F.concat(*[based(p, label) for p, label in BASE])
    fourth = third.withColumn("kept", F.when(F.size("found") > 0, F.aggregate("found", state, step))).withColumn("base", F.when(norm.isNotNull(), places))
    base_labels = F.coalesce(F.transform("base", lambda b: b["label"]), F.array().cast("array<string>"))
    all_labels = F.concat(base_labels, F.coalesce(F.transform("kept.kept", lambda d: d["label"]), F.array().cast("array<string>")))
    joined = lambda c: F.array_join(F.array_sort(F.array_distinct(c)), ",")
    return fourth.select(
        "row.*", "n_words", F.coalesce(F.size("base"), F.lit(0)).cast("long").alias("n_base"),
        F.array_min(F.transform("base", lambda b: b["at"])).alias("first_word"), F.array_max(F.transform("base", lambda b: b["at"])).alias("last_word"),
        joined(base_labels).alias("base_labels"), joined(all_labels).alias("labels"),
        F.when(F.col("kept").isNotNull(), F.least(F.lit(1.0), F.col("kept.covered") / F.col("n_words"))).otherwise(0.0).alias("score"),
        F.transform("kept.kept", lambda d: F.struct(d["label"].alias("label"), d["start"].alias("first_word"), (d["start"] - d["minus"]).alias("end_word"), d["priority"].alias("priority"))).alias("detections"),
    )


def _json(table_: list[tuple[str, int, int, list[str], str]]) -> str:
    import json

    return json.dumps([{"label": a, "priority": b, "rule": c, "keys": d, "body": e} for a, b, c, d, e in table_])


def op5_signature_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents", "doc_id", "text")).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score")
