"""Licence scan by sentence rules.

Each text is cut at ends of sentences and normalised (A-Z lower-cased, runs of other signs than letters, digits and bytes beyond ASCII to one
space). A line end, with blank lines and comment signs around it, may end a sentence or only wrap it: the longest run of whole lines that is a
known licence sentence is taken, and what is unknown becomes one gap. A copyright line with its years and holder is one sentence whatever they
are, and the numbers of a list are none. The sequence of identifiers is then matched, leftmost and longest rule first, against ordered rules, each a
licence's run of sentences.

Only DataFrame functions; no shuffle. Null and empty texts have no sentences: empty strings. Repeated rows are scanned alike. Columns of the
input named like the results are replaced, others never clash; an empty table gives no rows.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from repeatfold.llm.common import fresh

# Known sentences, normalised, and their identifiers.
SENTENCES = {
    "all rights reserved": "reserved",
    "released under the mit license": "mit_ref",
    "licensed under the mit license": "mit_ref",
    "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction": "mit_grant",
    "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software": "mit_notice",
    "the software is provided as is without warranty of any kind": "as_is",
    "licensed under the apache license version 2 0": "apache2_ref",
    "you may not use this file except in compliance with the license": "apache2_comply",
    "you may obtain a copy of the license at http www apache org licenses license 2 0": "apache2_copy",
    "this work is licensed under the gnu general public license version 3": "gpl3_ref",
    "this program is free software": "gpl_free",
    "licensed under cc by nc 4 0": "cc_by_nc4_ref",
    "licensed under cc by 4 0": "cc_by4_ref",
    "licensed under cc by sa 4 0": "cc_by_sa4_ref",
    "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met": "bsd_grant",
    "this software is in the public domain": "public_domain",
    "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer": "bsd_source",
    "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution": "bsd_binary",
    "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission": "bsd_names",
    "this software is provided by the copyright holders and contributors as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed": "bsd_as_is",
    "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies": "isc_grant",
    "the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness": "isc_as_is",
    "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation": "gpl_terms",
    "either version 2 of the license or at your option any later version": "gnu2_later",
    "either version 3 of the license or at your option any later version": "gnu3_later",
    "this library is free software": "lgpl_free",
    "you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation": "lgpl_terms",
    "either version 2 1 of the license or at your option any later version": "gnu21_later",
    "this source code form is subject to the terms of the mozilla public license v": "mpl_ref",
    "if a copy of the mpl was not distributed with this file you can obtain one at https mozilla org mpl 2 0": "mpl2_copy",
    "this is free and unencumbered software released into the public domain": "unlicense",
    "to the extent possible under law the person who associated cc0 with this work has waived all copyright and related or neighboring rights to this work": "cc0_waiver",
}
# The sentences as whole licence texts have them, and usual variants.
_GRANT, _NOTICE, _AS_IS = (next(k for k, v in SENTENCES.items() if v == name) for name in ("mit_grant", "mit_notice", "as_is"))
_RIGHTS = "including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions"
_DAMAGES = "express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and"
_CC = {"attribution 4 0": "cc_by4_ref", "attribution noncommercial 4 0": "cc_by_nc4_ref", "attribution sharealike 4 0": "cc_by_sa4_ref"}
VARIANTS = {
    f"{_GRANT} {_RIGHTS}": "mit_grant",
    _NOTICE.replace("permission notice", "permission notice including the next paragraph"): "mit_notice",
    f"{_AS_IS} {_DAMAGES} noninfringement": "as_is",
    f"{_AS_IS} {_DAMAGES} non infringement": "as_is",
    f"{_AS_IS} express or implied": "as_is",
    "licensed under the apache license version 2 0 the license": "apache2_ref",
    "the asf licenses this file to you under the apache license version 2 0 the license": "apache2_ref",
    **{f"you may obtain a copy of the license at {http} {www}apache org licenses license 2 0{end}": "apache2_copy" for http in ("http", "https") for www in ("www ", "") for end in ("", " html", " txt")},
    "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation": "gpl_free",
    **{f"this work is licensed under {a} creative commons {name} international license": k for a in ("a", "the") for name, k in _CC.items()},
}
# Licences and the ordered sentences that make them; an empty one is a gap (a version cut off as a sentence of its own).
RULES = [
    ("MIT", ("mit_grant", "mit_notice", "as_is")),
    ("MIT", ("mit_grant", "mit_notice")),
    ("MIT", ("mit_ref",)),
    ("Apache-2.0", ("apache2_ref", "apache2_comply", "apache2_copy")),
    ("Apache-2.0", ("apache2_ref",)),
    ("GPL-3.0", ("gpl3_ref",)),
    ("GPL-any", ("gpl_free",)),
    ("CC-BY-NC-4.0", ("cc_by_nc4_ref",)),
    ("CC-BY-4.0", ("cc_by4_ref",)),
    ("CC-BY-SA-4.0", ("cc_by_sa4_ref",)),
    ("BSD-like", ("bsd_grant",)),
    ("BSD-3-Clause", ("bsd_grant", "bsd_source", "bsd_binary", "bsd_names", "bsd_as_is")),
    ("BSD-3-Clause", ("bsd_grant", "bsd_source", "bsd_binary", "bsd_names")),
    ("BSD-2-Clause", ("bsd_grant", "bsd_source", "bsd_binary", "bsd_as_is")),
    ("BSD-2-Clause", ("bsd_grant", "bsd_source", "bsd_binary")),
    ("ISC", ("isc_grant", "isc_as_is")),
    ("ISC", ("isc_grant",)),
    ("GPL-2.0-or-later", ("gpl_free", "gpl_terms", "gnu2_later")),
    ("GPL-3.0-or-later", ("gpl_free", "gpl_terms", "gnu3_later")),
    ("LGPL-2.1-or-later", ("lgpl_free", "lgpl_terms", "gnu21_later")),
    ("LGPL-3.0-or-later", ("lgpl_free", "lgpl_terms", "gnu3_later")),
    ("MPL-2.0", ("mpl_ref", "", "mpl2_copy")),
    ("MPL-any", ("mpl_ref",)),
    ("Unlicense", ("unlicense",)),
    ("CC0-1.0", ("cc0_waiver",)),
    ("Public-domain", ("public_domain",)),
    ("Proprietary", ("reserved",)),
]
#: Normalised copyright lines, and what numbers an item of a list.
COPYRIGHT = r"^copyright (?:c )?[0-9]{4}(?: .*)?$"
ITEM = r"^(?:[0-9]{1,2}|[a-z]|[ivx]{1,4})$"
END = r"[.!?;:]+(?:[ \t\n\r\f\x0B]|\z)"
SIGNS = r"[\x00-/:-@\[-`{-\x7F]+"
_SIGNS_IN_LINE = r"[\x00-\x09\x0B\x0C\x0E-/:-@\[-`{-\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _pattern(rules: list[tuple[str, tuple[str, ...]]]) -> str:
    return "|".join(sorted(("".join(f"<{s}>" for s in ids) for _, ids in rules), key=lambda p: (-len(p), p)))


def _pieces(sentences: dict[str, str]) -> str:
    """From a line's beginning: the longest known sentence over whole lines, else the line."""
    keys = sorted(filter(None, sentences), key=lambda k: (-len(k), k))
    wrapped = "|".join("[ \n]".join(map(re.escape, k.split(" "))) for k in keys)
    return rf"(?:{wrapped})(?![^\n])|[^\n]+"


def sentence_ids(text: Column, sentences: dict[str, str] | None = None) -> Column:
    """Identifiers of a text's sentences in order, as ``<id>`` items in one string, with ``<>`` for each gap."""
    sentences = sentences or SENTENCES | VARIANTS
    known = F.create_map(*[F.lit(x) for k, v in sentences.items() for x in (k, f"<{v}>")])
    cut = F.split(F.regexp_replace(F.translate(text, _UPPER, _LOWER), END, "\x01"), "\x01")
    # signs to one space, then line ends with what is around them to one line end
    plain = lambda s: F.regexp_replace(F.regexp_replace(s, _SIGNS_IN_LINE, " "), " ?[\n\r][ \n\r]*", "\n")
    parts = F.flatten(F.transform(cut, lambda s: F.regexp_extract_all(F.btrim(plain(s), F.lit(" \n")), F.lit(_pieces(sentences)), F.lit(0))))
    named = lambda s: F.when(s.rlike(ITEM), "").when(s.rlike(COPYRIGHT), "<copyright>").otherwise("<>")
    ids = F.transform(parts, lambda s: F.coalesce(F.try_element_at(known, F.translate(s, "\n", " ")), named(s)))
    return F.regexp_replace(F.array_join(ids, ""), "(?:<>)+", "<>")


def scan(df: DataFrame, text_col: str = "text", sentences: dict[str, str] | None = None, rules: list | None = None) -> DataFrame:
    """``df`` with ``sentence_ids`` (known ones in order, comma-joined), ``n_sentences`` (known, but for copyright lines), ``licenses`` (matched rules in order, comma-joined)."""
    rules = rules or RULES
    names = F.create_map(*[F.lit(x) for name, ids in rules for x in ("".join(f"<{s}>" for s in ids), name)])
    text = F.col(text_col)
    # every known sentence holds one of these words, so a text without any has none
    words = sorted({min((w for w in s.split() if len(w) > 5), key=lambda w: (w not in _HINTS, w)) for s in (sentences or SENTENCES | VARIANTS)} | {"copyright"})
    maybe = F.translate(text, _UPPER, _LOWER).rlike("|".join(words))
    ids, known, hits = fresh(df, "_ids", "_known", "_hits")
    out = df.withColumn(ids, F.when(maybe, sentence_ids(text, sentences)).otherwise(F.lit("")))
    out = out.withColumn(known, F.regexp_extract_all(ids, F.lit("<([^<>]+)>"), F.lit(1)))
    out = out.withColumn(hits, F.regexp_extract_all(ids, F.lit("(" + _pattern(rules) + ")"), F.lit(1)))
    return out.withColumns({
        "sentence_ids": F.coalesce(F.array_join(known, ","), F.lit("")),
        "n_sentences": F.coalesce(F.size(F.filter(known, lambda x: x != "copyright")), F.lit(0)).cast("long"),
        "licenses": F.coalesce(F.array_join(F.transform(hits, lambda h: F.try_element_at(names, h)), ","), F.lit("")),
    }).drop(ids, known, hits)


_HINTS = {"license", "redistributions", "mozilla", "neither", "unencumbered", "extent", "either", "licensed", "reserved", "permission", "copyright", "software", "redistribution", "provided", "program"}


def scan_sql(table: str = "documents") -> str:
    """The same scan as one DuckDB statement."""
    q = lambda s: "'" + s.replace("'", "''") + "'"
    known = "MAP {" + ", ".join(f"{q(k)}: {q(f'<{v}>')}" for k, v in SENTENCES.items()) + "}"
    names = "MAP {" + ", ".join(f"{q(''.join(f'<{s}>' for s in ids))}: {q(n)}" for n, ids in dict.fromkeys((n, i) for n, i in RULES)) + "}"
    return f"""
with lines as (select doc_id, list_filter(list_transform(regexp_split_to_array(regexp_replace(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '{END}', chr(10), 'g'), '[\\n\\r]'),
  lambda s: trim(regexp_replace(s, '{SIGNS}', ' ', 'g'))), lambda s: s <> '') as l from {table}),
ids as (select doc_id, coalesce(array_to_string(list_transform(l, lambda s: coalesce({known}[s], case when regexp_matches(s, '{ITEM}') then '' when regexp_matches(s, '{COPYRIGHT}') then '<copyright>' else '<>' end)), ''), '') as i from lines),
seq as (select doc_id, regexp_replace(i, '(?:<>)+', '<>', 'g') as i from ids)
select doc_id, coalesce(array_to_string(regexp_extract_all(i, '<([^<>]+)>', 1), ','), '') as sentence_ids,
  len(list_filter(regexp_extract_all(i, '<([^<>]+)>', 1), lambda x: x <> 'copyright'))::bigint as n_sentences,
  coalesce(array_to_string(list_transform(regexp_extract_all(i, '({_pattern(RULES)})', 1), lambda h: {names}[h]), ','), '') as licenses
from seq"""
