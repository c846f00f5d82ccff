"""Licence scan by sentence rules, with DataFrame functions only.

A text's sentences are normalised and looked up among known licence sentences; a licence is found
where its ordered rule, a sequence of sentence identifiers, occurs in the text's identifier sequence.
"""

from __future__ import annotations

from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import let

#: Normalised sentences of well-known licence notices, by identifier.
SENTENCES = {
    "mit_short": "released under the mit license",
    "mit_licensed": "licensed under the mit license",
    "mit_title": "the mit license mit",
    "mit_grant": "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions",
    "mit_notice": "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    "as_is": "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement",
    "apache_short": "licensed under the apache license version 2 0",
    "apache_the_license": "licensed under the apache license version 2 0 the license",
    "apache_use": "you may not use this file except in compliance with the license",
    "apache_copy": "you may obtain a copy of the license at",
    "gpl3_work": "this work is licensed under the gnu general public license version 3",
    "gpl_free": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    "gpl_hope": "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    "bsd_grant": "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    "bsd_source": "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
    "bsd_binary": "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution",
    "cc_by_nc_4": "licensed under cc by nc 4 0",
    "cc_by_4": "licensed under cc by 4 0",
    "cc_by_sa_4": "licensed under cc by sa 4 0",
    "cc0": "licensed under cc0 1 0",
    "mpl2": "this source code form is subject to the terms of the mozilla public license v 2 0",
    "apache_unless": "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    "gpl2_free": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version",
    "gpl2_only": "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license version 2 as published by the free software foundation",
    "gpl_copy": "you should have received a copy of the gnu general public license along with this program",
    "lgpl21_free": "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 2 1 of the license or at your option any later version",
    "lgpl3_free": "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    "lgpl_hope": "this library is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    "agpl3_free": "this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    "bsd_names": "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    "bsd_as_is": "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed",
    "isc_grant": "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    "isc_as_is": "the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness",
    "unlicense_public": "this is free and unencumbered software released into the public domain",
    "unlicense_anyone": "anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary for any purpose commercial or non commercial and by any means",
    "epl2": "this program and the accompanying materials are made available under the terms of the eclipse public license 2 0 which is available at",
    "epl2_available": "this program and the accompanying materials are made available under the terms of the eclipse public license 2 0",
    "mpl2_copy": "if a copy of the mpl was not distributed with this file you can obtain one at",
    "mpl11": "the contents of this file are subject to the mozilla public license version 1 1 the license",
    "zlib_as_is": "this software is provided as is without any express or implied warranty",
    "zlib_event": "in no event will the authors be held liable for any damages arising from the use of this software",
    "zlib_grant": "permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions",
    "boost_short": "distributed under the boost software license version 1 0",
    "boost_grant": "permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license the software to use reproduce display distribute execute and transmit the software",
    "artistic2": "this program is free software you can redistribute it and or modify it under the terms of the artistic license 2 0",
    "wtfpl": "you just do what the fuck you want to",
    "ofl11": "this font software is licensed under the sil open font license version 1 1",
    "cddl1": "the contents of this file are subject to the terms of the common development and distribution license the license",
    "psf2": "licensed under the python software foundation license version 2",
    "cc_by_3": "licensed under cc by 3 0",
    "cc_by_nd_4": "licensed under cc by nd 4 0",
    "cc_by_nc_sa_4": "licensed under cc by nc sa 4 0",
    "cc_by_nc_nd_4": "licensed under cc by nc nd 4 0",
    "cc_by_long": "this work is licensed under a creative commons attribution 4 0 international license",
    "cc_by_sa_long": "this work is licensed under a creative commons attribution sharealike 4 0 international license",
    "cc_by_nc_long": "this work is licensed under a creative commons attribution noncommercial 4 0 international license",
    "cc0_long": "the person who associated a work with this deed has dedicated the work to the public domain by waiving all of his or her rights to the work worldwide under copyright law",
    "spdx_mit": "spdx license identifier mit",
    "spdx_apache2": "spdx license identifier apache 2 0",
    "spdx_gpl2": "spdx license identifier gpl 2 0 only",
    "spdx_gpl2_later": "spdx license identifier gpl 2 0 or later",
    "spdx_gpl3": "spdx license identifier gpl 3 0 only",
    "spdx_gpl3_later": "spdx license identifier gpl 3 0 or later",
    "spdx_bsd2": "spdx license identifier bsd 2 clause",
    "spdx_bsd3": "spdx license identifier bsd 3 clause",
    "spdx_isc": "spdx license identifier isc",
    "spdx_mpl2": "spdx license identifier mpl 2 0",
}
#: Fixed values: (licence, ordered sentence identifiers, how many other licence sentences may stand between two of them).
RULES = (
    ("MIT", ("mit_short",), 0),
    ("MIT", ("mit_licensed",), 0),
    ("MIT", ("mit_grant", "mit_notice", "as_is"), 1),
    ("Apache-2.0", ("apache_short",), 0),
    ("Apache-2.0", ("apache_the_license", "apache_use", "apache_copy"), 1),
    ("GPL-3.0", ("gpl3_work",), 0),
    ("GPL-3.0-or-later", ("gpl_free", "gpl_hope"), 1),
    ("BSD-2-Clause", ("bsd_grant", "bsd_source", "bsd_binary"), 1),
    ("CC-BY-NC-4.0", ("cc_by_nc_4",), 0),
    ("CC-BY-4.0", ("cc_by_4",), 0),
    ("CC-BY-SA-4.0", ("cc_by_sa_4",), 0),
    ("CC0-1.0", ("cc0",), 0),
    ("MPL-2.0", ("mpl2",), 0),
    ("GPL-2.0-or-later", ("gpl2_free", "gpl_hope"), 1),
    ("GPL-2.0-only", ("gpl2_only", "gpl_hope"), 1),
    ("LGPL-2.1-or-later", ("lgpl21_free", "lgpl_hope"), 1),
    ("LGPL-3.0-or-later", ("lgpl3_free", "lgpl_hope"), 1),
    ("AGPL-3.0-or-later", ("agpl3_free", "gpl_hope"), 1),
    ("BSD-3-Clause", ("bsd_grant", "bsd_source", "bsd_binary", "bsd_names"), 1),
    ("ISC", ("isc_grant", "isc_as_is"), 1),
    ("Unlicense", ("unlicense_public", "unlicense_anyone"), 1),
    ("EPL-2.0", ("epl2",), 0),
    ("EPL-2.0", ("epl2_available",), 0),
    ("MPL-1.1", ("mpl11",), 0),
    ("Zlib", ("zlib_as_is", "zlib_event", "zlib_grant"), 1),
    ("BSL-1.0", ("boost_short",), 0),
    ("BSL-1.0", ("boost_grant",), 0),
    ("Artistic-2.0", ("artistic2",), 0),
    ("WTFPL", ("wtfpl",), 0),
    ("OFL-1.1", ("ofl11",), 0),
    ("CDDL-1.0", ("cddl1",), 0),
    ("PSF-2.0", ("psf2",), 0),
    ("CC-BY-3.0", ("cc_by_3",), 0),
    ("CC-BY-ND-4.0", ("cc_by_nd_4",), 0),
    ("CC-BY-NC-SA-4.0", ("cc_by_nc_sa_4",), 0),
    ("CC-BY-NC-ND-4.0", ("cc_by_nc_nd_4",), 0),
    ("CC-BY-4.0", ("cc_by_long",), 0),
    ("CC-BY-SA-4.0", ("cc_by_sa_long",), 0),
    ("CC-BY-NC-4.0", ("cc_by_nc_long",), 0),
    ("CC0-1.0", ("cc0_long",), 0),
    ("MIT", ("spdx_mit",), 0),
    ("Apache-2.0", ("spdx_apache2",), 0),
    ("GPL-2.0-only", ("spdx_gpl2",), 0),
    ("GPL-2.0-or-later", ("spdx_gpl2_later",), 0),
    ("GPL-3.0-only", ("spdx_gpl3",), 0),
    ("GPL-3.0-or-later", ("spdx_gpl3_later",), 0),
    ("BSD-2-Clause", ("spdx_bsd2",), 0),
    ("BSD-3-Clause", ("spdx_bsd3",), 0),
    ("ISC", ("spdx_isc",), 0),
    ("MPL-2.0", ("spdx_mpl2",), 0),
)
ENDS = r"\n+|(?<=[.!?;:])[\x20\x09-\x0D]+"


def marks(known: dict[str, str]) -> str:
    """A pattern that every text with a known sentence fits: pairs of neighbouring words, so few that each sentence has one of them.

    Pairs that many sentences share come first, and long ones, which other prose seldom has. Words of a normalised sentence stand in the
    text as they are, but for their case and for what parts them.
    """
    pairs = [set(zip(w, w[1:], strict=False)) or {(w[0],)} for s in known.values() if (w := s.split())]
    chosen = []
    while pairs:
        often = Counter(p for s in pairs for p in s)
        chosen.append(max(often, key=lambda p: (often[p] * min(sum(map(len, p)), 16) ** 2, p)))
        pairs = [s for s in pairs if chosen[-1] not in s]
    return "(?iu)" + "|".join("(?-iu:[^a-zA-Z0-9]+)".join(p) for p in chosen) if chosen else r"\A\z(?!)"


def _normal(sentence: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(sentence), "[^a-z0-9]+", " "))


def _identifiers(text: Column, known: dict[str, str]) -> Column:
    """The identifiers of the text's known sentences, in order."""
    ids = list(known)
    normal = F.array(*[F.lit(known[i]) for i in ids])
    names = F.array(*[F.lit(i) for i in ids])
    plausible = F.filter(F.split(text, ENDS), lambda s: s.rlike(marks(known)))
    places = F.transform(plausible, lambda s: F.array_position(normal, _normal(s)).cast("int"))
    return F.transform(F.filter(places, lambda p: p > 0), lambda p: F.element_at(names, p))


def _pattern(ids: tuple[str, ...], between: int) -> str:
    """For identifiers that each stand between blanks of their own."""
    return f"(?: [a-z0-9_]+ ){{0,{between}}}".join(f" {i} " for i in ids)


def license_scan(docs: DataFrame, known: dict[str, str] = SENTENCES, rules: tuple = RULES) -> DataFrame:
    """docs(doc_id, text, ...) -> doc_id, sentence_ids (joined by blanks), licenses (sorted, joined by commas), n_licenses.

    One row for each row. Sentences end at line breaks and at ".", "!", "?", ";" or ":" before white space.
    Long notices are wrapped: where a text as it stands and the same with single line breaks folded differ, each
    is matched and the licences united; sentence_ids is the longer of both (the first on ties).
    Null and empty texts, and texts without a known sentence, have empty strings and 0.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    marked = F.when(text.rlike(marks(known)), text).otherwise(F.lit(""))
    folded = F.regexp_replace("_x", r"(?<![\n.!?;:])\n(?!\n)", " ")
    found = docs.select("doc_id", marked.alias("_x")).select(
        "doc_id",
        _identifiers(F.col("_x"), known).alias("_lines"),
        F.when(F.col("_x") == "", F.array().cast("array<string>")).otherwise(_identifiers(folded, known)).alias("_folded"),
    )

    def matched(ids: Column) -> Column:
        spaced = F.concat(F.lit(" "), F.array_join(ids, "  "), F.lit(" "))
        return let(spaced, lambda s: F.array_compact(F.array(*[F.when(s.rlike(_pattern(r, n)), F.lit(name)) for name, r, n in rules])))

    licenses = F.array_sort(F.array_union(matched(F.col("_lines")), matched(F.col("_folded"))))
    longer = F.when(F.size("_folded") > F.size("_lines"), F.col("_folded")).otherwise(F.col("_lines"))
    return found.select(
        "doc_id",
        F.array_join(longer, " ").alias("sentence_ids"),
        F.when((F.size("_lines") == 0) & (F.size("_folded") == 0), F.array().cast("array<string>")).otherwise(licenses).alias("_l"),
    ).select("doc_id", "sentence_ids", F.array_join("_l", ",").alias("licenses"), F.size("_l").cast("long").alias("n_licenses"))
