"""Licence scans by sentence rules (operator 2).

Known licence sentences have identifiers; a licence is a rule: an ordered sequence of identifiers. A known sentence is
found where its words (A-Z lower-cased) follow one another with anything but letters, digits, stops and blank lines
between them, so also where it is wrapped or its lines begin with comment marks. It begins at a line or after a full stop,
question or exclamation mark before white space, perhaps behind an item's number, and ends at a line end or such a mark.
Known sentences become their identifiers, all else is left out, and the identifier sequence is met with the rules, longer
ones first: a rule takes the sentences that it matches.
All of it runs in the row, without a shuffle: the known sentences are part of the plan and their number is fixed.

Defined results: a null or empty text, or one without known sentences, has no licences (an empty list); a rule that
matches more than once is reported once; a rule whose match lies in a longer rule's match is reported too; repeated
rows are scanned row by row; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Known sentences, normalised, by identifier.
SENTENCES = {
    "mit-release": "released under the mit license",
    "mit-licensed": "licensed under the mit license",
    "mit-grant": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions",
    "mit-notice": "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    "apache2-licensed": "licensed under the apache license version 2.0",
    "apache2-comply": "you may not use this file except in compliance with the license",
    "apache2-copy": "you may obtain a copy of the license at http www.apache.org licenses license 2.0",
    "gpl3-work": "this work is licensed under the gnu general public license version 3",
    "gpl-redistribute": "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    "gpl-warranty": "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    "ccbync4": "licensed under cc by nc 4.0",
    "ccby4": "licensed under cc by 4.0",
    "ccbysa4": "licensed under cc by sa 4.0",
    "bsd-retain": "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
    "bsd-binary": "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution",
    "bsd-names": "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    "all-rights": "all rights reserved",
    "apache2-notice": "licensed under the apache license version 2.0 the license you may not use this file except in compliance with the license",
    "apache2-obtain": "you may obtain a copy of the license at",
    "apache2-url": "http www.apache.org licenses license 2.0",
    "apache2-urls": "https www.apache.org licenses license 2.0",
    "gpl-program": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version",
}
SENTENCES |= {
    "gpl2-program": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version",
    "gpl2-only": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license version 2 as published by the free software foundation",
    "agpl3-program": "this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    "lgpl21-library": "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 2.1 of the license or at your option any later version",
    "lgpl3-library": "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    "lgpl-warranty": "this library is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    "mpl2-terms": "this source code form is subject to the terms of the mozilla public license v. 2.0",
    "mpl2-copy": "if a copy of the mpl was not distributed with this file you can obtain one at https mozilla.org mpl 2.0",
    "isc-grant": "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    "unlicense": "this is free and unencumbered software released into the public domain",
    "zlib-grant": "permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions",
    "boost": "distributed under the boost software license version 1.0",
    "epl2": "this program and the accompanying materials are made available under the terms of the eclipse public license 2.0 which is available at https www.eclipse.org legal epl 2.0",
    "bsd-names-university": "neither the name of the university nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    "bsd-names-plural": "neither the name of the copyright holders nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    "bsd-advertising": "all advertising materials mentioning features or use of this software must display the following acknowledgement",
}
#: Whole sentences about a work: subject, verb and licence, by the identifier of the licence's own short sentence.
SUBJECTS = ("project", "software", "work", "program", "library", "package", "code", "file", "repository")
NAMED = {"mit-licensed": "MIT", "apache2-licensed": "Apache-2.0", "ccbync4": "CC-BY-NC-4.0", "ccby4": "CC-BY-4.0", "ccbysa4": "CC-BY-SA-4.0"}
STATED = {f"{i}-{verb}-{x}": (n, f"this {x} is {verb} {SENTENCES[i].split(' ', 1)[1]}") for i, n in NAMED.items() for verb in ("licensed", "released") for x in SUBJECTS}
#: The notice of the attribution licences, by the names of their conditions.
CONDITIONS = {"BY": "attribution", "BY-SA": "attribution sharealike", "BY-ND": "attribution noderivatives", "BY-NC": "attribution noncommercial", "BY-NC-SA": "attribution noncommercial sharealike", "BY-NC-ND": "attribution noncommercial noderivatives"}
STATED |= {f"cc-{c.lower()}-{version}": (f"CC-{c}-{version}", f"this work is licensed under a creative commons {words} {version} {where} license") for c, words in CONDITIONS.items() for version, where in (("4.0", "international"), ("3.0", "unported"))}
#: Identifiers that stand in a line of their own in source files.
SPDX = ("MIT", "Apache-2.0", "BSD-2-Clause", "BSD-3-Clause", "0BSD", "ISC", "Zlib", "Unlicense", "BSL-1.0", "MPL-2.0", "EPL-2.0", "CC0-1.0", "CC-BY-4.0", "CC-BY-SA-4.0", "CC-BY-NC-4.0", "GPL-2.0-only", "GPL-2.0-or-later", "GPL-3.0-only", "GPL-3.0-or-later", "LGPL-2.1-only", "LGPL-2.1-or-later", "LGPL-3.0-only", "LGPL-3.0-or-later", "AGPL-3.0-only", "AGPL-3.0-or-later")
STATED |= {f"spdx-{n.lower()}": (n, "spdx license identifier " + n.lower().replace("-", " ")) for n in SPDX}
SENTENCES |= {i: s for i, (_, s) in STATED.items()}
#: Licence and the identifiers that must follow one another (unknown sentences between them don't count).
RULES = (
    ("MIT", ("mit-release",)),
    ("MIT", ("mit-licensed",)),
    ("MIT", ("mit-grant", "mit-notice")),
    ("Apache-2.0", ("apache2-licensed",)),
    ("Apache-2.0", ("apache2-comply", "apache2-copy")),
    ("GPL-3.0", ("gpl3-work",)),
    ("GPL-3.0", ("gpl-redistribute", "gpl-warranty")),
    ("CC-BY-NC-4.0", ("ccbync4",)),
    ("CC-BY-4.0", ("ccby4",)),
    ("CC-BY-SA-4.0", ("ccbysa4",)),
    ("BSD-3-Clause", ("bsd-retain", "bsd-binary", "bsd-names")),
    ("BSD-3-Clause", ("bsd-retain", "bsd-binary", "bsd-names-university")),
    ("BSD-3-Clause", ("bsd-retain", "bsd-binary", "bsd-names-plural")),
    ("BSD-4-Clause", ("bsd-retain", "bsd-binary", "bsd-advertising", "bsd-names")),
    ("BSD-4-Clause", ("bsd-retain", "bsd-binary", "bsd-advertising", "bsd-names-university")),
    ("BSD-2-Clause", ("bsd-retain", "bsd-binary")),
    ("Proprietary", ("all-rights",)),
    ("Apache-2.0", ("apache2-notice",)),
    ("Apache-2.0", ("apache2-comply", "apache2-obtain", "apache2-url")),
    ("Apache-2.0", ("apache2-comply", "apache2-obtain", "apache2-urls")),
    ("GPL-3.0", ("gpl-program", "gpl-warranty")),
    ("GPL-2.0", ("gpl2-program", "gpl-warranty")),
    ("GPL-2.0", ("gpl2-only", "gpl-warranty")),
    ("AGPL-3.0", ("agpl3-program", "gpl-warranty")),
    ("LGPL-2.1", ("lgpl21-library", "lgpl-warranty")),
    ("LGPL-3.0", ("lgpl3-library", "lgpl-warranty")),
    ("MPL-2.0", ("mpl2-terms", "mpl2-copy")),
    ("ISC", ("isc-grant",)),
    ("Unlicense", ("unlicense",)),
    ("Zlib", ("zlib-grant",)),
    ("BSL-1.0", ("boost",)),
    ("EPL-2.0", ("epl2",)),
    *((n, (i,)) for i, (n, _) in STATED.items()),
)
#: Sentence ends, and what a normalised sentence replaces by one space, as both engines' patterns.
ENDS = r"[\n\r]+|[.!?]+[ \t]+|[.!?]+$"
NOISE = r"[^a-z0-9.]+"


def sentence_ids(text: Column, sentences: dict[str, str] | None = None) -> Column:
    """Identifiers of the known sentences of a text, in order.

    Only texts with one of the sentences' first two words side by side go through the long pattern.
    """
    sentences = sentences or SENTENCES
    known = F.create_map(*[F.lit(x) for name, s in sentences.items() for x in (s, name)])
    low = F.translate(F.coalesce(text, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    found = F.when(low.rlike(_starts(sentences)), F.regexp_extract_all(low, F.lit(_pattern(sentences)), F.lit(1))).otherwise(F.array().cast("array<string>"))
    plain = F.transform(found, lambda s: F.trim(F.regexp_replace(s, NOISE, " ")))
    return F.filter(F.transform(plain, lambda s: F.try_element_at(known, s)), lambda i: i.isNotNull())


#: Between two words: no letter, digit, stop or blank line; a line end at most.
_GAP = r"(?:[^a-z0-9.!?\r\n]|[!?](?!\s))*+(?:(?:\r\n?|\n)(?:[^a-z0-9.!?\r\n]|[!?](?!\s))*+)?(?<![a-z0-9.])"


def _starts(sentences: dict[str, str]) -> str:
    """Pattern that every text with a known sentence meets: the first two words of one of them."""
    return "(" + "|".join(sorted({"[^a-z0-9.]+".join(s.replace(".", r"\.").split()[:2]) for s in sentences.values()})) + ")"


def _pattern(sentences: dict[str, str]) -> str:
    """Pattern of all known sentences, longer ones first, between their ends."""
    body = "|".join(_GAP.join(s.replace(".", r"\.").split()) for s in sorted(sentences.values(), key=len, reverse=True))
    return rf"(?:^|[\r\n]|[.!?][ \t])[^a-z0-9.]*+(?:[a-z0-9]{{1,2}}\)[^a-z0-9.]*+)?({body})(?=[^a-z0-9\r\n]*(?:[\r\n]|(?![\s\S]))|[^a-z0-9\r\n]*[.!?][ \t])"


def in_order(rules=None) -> list[tuple[str, str]]:
    """(licence, ' identifier identifier ... ') of the rules, longer ones first: a rule takes the sentences it matches."""
    return [(name, " " + " ".join(ids) + " ") for name, ids in sorted(rules or RULES, key=lambda r: -len(r[1]))]


def matched(ids: Column, rules=None) -> Column:
    """Sorted licences whose rule's identifiers stand one after the other in ``ids``. A longer rule goes first and takes
    its sentences, so they count for no shorter one."""
    ordered = F.array(*[F.struct(F.lit(n).alias("name"), F.lit(q).alias("ids")) for n, q in in_order(rules)])
    begin = F.struct(F.concat(F.lit(" "), F.array_join(ids, " "), F.lit(" ")).alias("line"), F.array().cast("array<string>").alias("found"))
    taken = lambda a, r: F.struct(F.replace(a["line"], r["ids"], F.lit(" | ")).alias("line"), F.array_append(a["found"], r["name"]).alias("found"))
    return F.array_sort(F.array_distinct(F.aggregate(ordered, begin, lambda a, r: F.when(F.contains(a["line"], r["ids"]), taken(a, r)).otherwise(a), lambda a: a["found"])))


def scan(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, sentence_ids, licenses, n_licenses."""
    ids = docs.select(F.col("doc_id").cast("long"), sentence_ids(F.col("text")).alias("sentence_ids"))
    return ids.withColumn("licenses", F.when(F.size("sentence_ids") > 0, matched(F.col("sentence_ids"))).otherwise(F.array().cast("array<string>"))).withColumn("n_licenses", F.size("licenses").cast("long"))
