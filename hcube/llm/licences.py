"""Licence scan by sentence rules, in DataFrame functions only.

Sentences are normalised and mapped to identifiers by a table of patterns; the
sequence of identifiers of a text is then matched against ordered rules, longer
ones first, each match using up its identifiers.  Identifiers left over are
reported, so an unknown combination is visible.

Defined results: null or empty texts have no sentences and no licences; very long texts
are judged whole; rows are judged one by one, so ties and repeated rows give equal
results; an empty table gives no rows; other columns of the input stay, and those named
``sentence_ids``, ``licences`` or ``leftover`` give way to the results.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Cheap test that a lower-cased text can hold a licence sentence at all; every
# pattern of SENTENCES needs one of these (tested entry by entry).
TRIGGER = (
    r"licen[sc]|copyright|warrant|permission|redistribut|spdx|endorse|reserved|unencumbered|dedication|"
    r"attribution|creative|be liable|cc0|cc[^\p{L}\p{N}.,()/]+by"
)

# Fixed values: (identifier, pattern over a normalised sentence), first match counts.
SENTENCES = (
    ("spdx-apache2", r"spdx license identifier apache 2\.0"),
    ("spdx-mit", r"spdx license identifier mit\b"),
    ("spdx-bsd3", r"spdx license identifier bsd 3 clause"),
    ("spdx-bsd2", r"spdx license identifier bsd 2 clause"),
    ("spdx-gpl3", r"spdx license identifier gpl 3\.0"),
    ("spdx-gpl2", r"spdx license identifier gpl 2\.0"),
    ("spdx-mpl2", r"spdx license identifier mpl 2\.0"),
    ("agpl", r"gnu affero general public license"),
    ("lgpl3", r"gnu lesser general public license,? (as published by the free software foundation, )?(either )?version 3"),
    ("lgpl21", r"gnu (lesser|library) general public license,? (as published by the free software foundation, )?(either )?version 2"),
    ("gpl3plus", r"gnu general public license.*version 3.*(or|any) (\(at your option\) )?(any )?later"),
    ("gpl2plus", r"gnu general public license.*version 2.*(or|any) (\(at your option\) )?(any )?later"),
    ("gpl3", r"gnu general public license.*version 3"),
    ("gpl2", r"gnu general public license.*version 2"),
    ("gplany", r"gnu general public license"),
    ("apache2", r"licensed under the apache license,? version 2"),
    ("apache-compliance", r"you may not use this file except in compliance with the license"),
    ("apache-copy", r"you may obtain a copy of the license at"),
    ("apache-asis", r"software distributed under the license is distributed on an as is basis"),
    ("mit-short", r"(released|licensed|distributed|available) under (the terms of )?the mit licen[sc]e"),
    ("mit-grant", r"permission is hereby granted, free of charge, to any person obtaining a copy of this software"),
    ("mit-notice", r"the above copyright notice and this permission notice shall be included in all copies"),
    ("mit-asis", r"the software is provided as is, without warranty of any kind, express or implied"),
    ("isc-grant", r"permission to use, copy, modify,? and/?or distribute this software for any purpose"),
    ("isc-asis", r"the software is provided as is and the author disclaims all warranties"),
    ("bsd-grant", r"redistribution and use in source and binary forms, with or without modification"),
    ("bsd-source", r"redistributions of source code must retain the above copyright notice"),
    ("bsd-binary", r"redistributions in binary form must reproduce the above copyright notice"),
    ("bsd-noendorse", r"neither the name of .*may be used to endorse or promote products"),
    ("bsd-asis", r"this software is provided by .*as is and any express or implied warranties"),
    ("liability", r"in no event shall .*be liable for any"),
    ("mpl2", r"mozilla public license,? v(ersion|\.) ?2\.0"),
    ("epl2", r"eclipse public license,? (v|version )2\.0"),
    ("cc-by-nc-nd", r"(cc by nc nd|attribution noncommercial noderivatives)"),
    ("cc-by-nc-sa", r"(cc by nc sa|attribution noncommercial sharealike)"),
    ("cc-by-nc", r"(cc by nc|attribution noncommercial)"),
    ("cc-by-nd", r"(cc by nd|attribution noderivatives)"),
    ("cc-by-sa", r"(cc by sa|attribution sharealike)"),
    ("cc-by", r"(licensed under|license) .*(cc by|creative commons attribution)"),
    ("cc0", r"(cc0|creative commons zero|public domain dedication)"),
    ("unlicense", r"this is free and unencumbered software released into the public domain"),
    ("all-rights", r"all rights reserved"),
)

# Fixed values: (licence, identifiers that must follow each other), longer rules first.
RULES = (
    ("BSD-3-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-noendorse", "bsd-asis", "liability")),
    ("BSD-3-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-noendorse", "bsd-asis")),
    ("BSD-2-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-asis", "liability")),
    ("MIT", ("mit-grant", "mit-notice", "mit-asis", "liability")),
    ("BSD-2-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-asis")),
    ("Apache-2.0", ("apache2", "apache-compliance", "apache-copy", "apache-asis")),
    ("MIT", ("mit-grant", "mit-notice", "mit-asis")),
    ("ISC", ("isc-grant", "isc-asis", "liability")),
    ("MIT", ("mit-grant", "mit-asis")), ("ISC", ("isc-grant", "isc-asis")),
    ("Apache-2.0", ("apache2",)), ("Apache-2.0", ("spdx-apache2",)),
    ("MIT", ("mit-short",)), ("MIT", ("spdx-mit",)),
    ("BSD-3-Clause", ("spdx-bsd3",)), ("BSD-2-Clause", ("spdx-bsd2",)),
    ("AGPL-3.0", ("agpl",)), ("LGPL-3.0", ("lgpl3",)), ("LGPL-2.1", ("lgpl21",)),
    ("GPL-3.0-or-later", ("gpl3plus",)), ("GPL-2.0-or-later", ("gpl2plus",)),
    ("GPL-3.0", ("gpl3",)), ("GPL-2.0", ("gpl2",)), ("GPL-3.0", ("spdx-gpl3",)), ("GPL-2.0", ("spdx-gpl2",)),
    ("GPL", ("gplany",)), ("MPL-2.0", ("mpl2",)), ("MPL-2.0", ("spdx-mpl2",)), ("EPL-2.0", ("epl2",)),
    ("CC-BY-NC-ND", ("cc-by-nc-nd",)), ("CC-BY-NC-SA", ("cc-by-nc-sa",)), ("CC-BY-NC", ("cc-by-nc",)),
    ("CC-BY-ND", ("cc-by-nd",)), ("CC-BY-SA", ("cc-by-sa",)), ("CC-BY", ("cc-by",)), ("CC0-1.0", ("cc0",)),
    ("Unlicense", ("unlicense",)),
)


def _lit(pattern: str) -> str:
    return pattern.replace("\\", "\\\\").replace("'", "\\'")


# A sentence ends at a stop before white space (not at that of "v. 2.0"), at an empty
# line, and at a line end before a line that begins a statement of its own.
_MARKS = r"[ \t/#*;!>%-]*"
_STATEMENT = (
    r"Copyright\b|COPYRIGHT \(|\([cC]\) ?\d|\u00a9|SPDX|Licensed|Released|Distributed under|Permission is|Permission to|Redistribution|"
    r"All rights|All Rights|ALL RIGHTS|This (program|software|file|library|work) is|Neither the name|CC[ -]BY|CC0|\d+[.)] |\([a-z0-9]\) "
)
_CUT = rf"(?<=[.!?])(?<!\b[vV]\.)\s+|\r?\n(?={_MARKS}\r?\n)|\r?\n(?={_MARKS}(?:{_STATEMENT}))"

# Of the identifiers of one family a sentence has the first in the table only.
_FAMILIES = (("agpl", "lgpl3", "lgpl21", "gpl3plus", "gpl2plus", "gpl3", "gpl2", "gplany"), ("cc-by-nc-nd", "cc-by-nc-sa", "cc-by-nc", "cc-by-nd", "cc-by-sa", "cc-by"))


def sentence_ids(text: str) -> str:
    """SQL for the identifiers of a text's sentences, in order of their places."""
    tidy = _lit(r"[^\p{L}\p{N}.,()/]+")
    wrap = _lit(r"\r?\n" + _MARKS)
    of = dict(SENTENCES)
    groups = [*_FAMILIES, *[(k,) for k in of if not any(k in f for f in _FAMILIES)]]
    found = ", ".join(
        "CASE " + " ".join(f"WHEN x RLIKE '{_lit(of[k])}' THEN struct(regexp_instr(x, '{_lit(of[k])}') AS at, '{k}' AS id)" for k in g) + " END" for g in groups
    )
    # Lines that have no end of their own may leave several statements in one sentence, so all are looked for.
    return (
        f"flatten(transform(transform(split({text}, '{_lit(_CUT)}'), "
        f"x -> trim(regexp_replace(regexp_replace(translate(lower(regexp_replace(x, '{wrap}', ' ')), ';', ','), '{tidy}', ' '), ' +([.,])', '$1'))), "
        f"x -> CASE WHEN NOT x RLIKE '{_lit(TRIGGER)}' AND NOT x RLIKE '{_lit(UNKNOWN)}' THEN cast(array() AS array<string>) "
        f"ELSE transform(array_sort(filter(array({found}), y -> y IS NOT NULL)), y -> y.id) END "
        f"|| CASE WHEN x RLIKE '{_lit(UNKNOWN)}' AND NOT ({' OR '.join(f"x RLIKE '{_lit(p)}'" for p in of.values())}) THEN array('unknown') ELSE cast(array() AS array<string>) END))"
    )


# A normalised sentence of no pattern that is about a licence all the same.
UNKNOWN = r"licen[sc]|copyright|warrant|permission|redistribut|spdx|as is|public domain|may obtain a copy|endorse"


def scan(docs: DataFrame, text: str = "text") -> DataFrame:
    """Adds ``sentence_ids``, ``licences`` and ``leftover`` (arrays of strings)."""
    own = [F.col(f"`{c}`") for c in docs.columns if c not in ("sentence_ids", "licences", "leftover", "__chain")]
    step = docs.select(
        *own,
        F.expr(
            f"CASE WHEN lower(`{text}`) RLIKE '{_lit(TRIGGER)}' THEN {sentence_ids(f'`{text}`')} "
            f"ELSE cast(array() as array<string>) END"
        ).alias("sentence_ids"),
    )
    # The identifiers as one string, each between semicolons; a rule that matches
    # leaves its licence in their place, so no later rule can use them again.
    chain = F.concat(F.lit(";"), F.array_join(F.col("sentence_ids"), ";;"), F.lit(";"))
    for name, ids in RULES:
        # Unknown sentences between them don't part the identifiers of a rule, and stay left over.
        between = "((?:;unknown;)*)".join(f";{k};" for k in ids)
        chain = F.regexp_replace(chain, F.lit(between), F.lit(f";={name};" + "".join(f"${i}" for i in range(1, len(ids)))))
    step = step.withColumn("__chain", F.when(F.size("sentence_ids") > 0, chain).otherwise(F.lit("")))
    parts = F.filter(F.split(F.col("__chain"), ";"), lambda x: x != "")
    return step.select(
        *own, "sentence_ids",
        F.transform(F.filter(parts, lambda x: x.startswith("=")), lambda x: F.substring(x, 2, 1000)).alias("licences"),
        F.filter(parts, lambda x: ~x.startswith("=")).alias("leftover"),
    )


def op7_licence_scan(docs: DataFrame) -> DataFrame:
    return scan(docs.select("doc_id", "text")).select(
        "doc_id",
        F.size("sentence_ids").cast("long").alias("n_sentences"),
        F.array_join("sentence_ids", ";").alias("sentence_ids"),
        F.array_join(F.array_distinct("licences"), ",").alias("licences"),
        F.array_join("leftover", ";").alias("leftover"),
    )
