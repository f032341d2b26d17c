"""Licence scans: known sentences become identifiers, and identifier sequences are matched against ordered rules.

DataFrame functions only, one narrow pass: nothing is shuffled, and the knowledge base is a literal of fixed size.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Sentences of public licence notices, with their identifiers.
SENTENCES = {
    "apache-line": "Licensed under the Apache License, Version 2.0.",
    "apache-head": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.',
    "apache-copy": "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
    "mit-line": "Released under the MIT License.",
    "mit-grant": 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:',
    "mit-notice": "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "gpl3-line": "This work is licensed under the GNU General Public License, version 3.",
    "gpl-free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "gpl-hope": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.",
    "cc-by-nc-line": "Licensed under CC BY-NC 4.0.",
    "cc-by-line": "Licensed under CC BY 4.0.",
    "bsd-grant": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "bsd-source": "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "bsd-binary": "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "bsd-names": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
}
# Rules in the order in which they are tried; a match uses up its sentences.
RULES = (
    ("BSD-3-Clause", "permissive", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-names")),
    ("BSD-2-Clause", "permissive", ("bsd-grant", "bsd-source", "bsd-binary")),
    ("Apache-2.0", "permissive", ("apache-head", "apache-copy")),
    ("GPL-3.0-or-later", "copyleft", ("gpl-free", "gpl-hope")),
    ("MIT", "permissive", ("mit-grant", "mit-notice")),
    ("GPL-3.0-or-later (part)", "copyleft", ("gpl-free",)),
    ("MIT (part)", "permissive", ("mit-grant",)),
    ("Apache-2.0 (part)", "permissive", ("apache-head",)),
    ("Apache-2.0 (line)", "permissive", ("apache-line",)),
    ("MIT (line)", "permissive", ("mit-line",)),
    ("GPL-3.0-only (line)", "copyleft", ("gpl3-line",)),
    ("CC-BY-NC-4.0 (line)", "noncommercial", ("cc-by-nc-line",)),
    ("CC-BY-4.0 (line)", "permissive", ("cc-by-line",)),
)


def normal(sentence: str) -> str:
    return re.sub(r"[^a-z0-9]+", " ", sentence.lower()).strip()


def pieces(sentence: str) -> list[str]:
    """The normalised pieces into which the scanner's own splitting would cut a known sentence."""
    return [p for x in re.sub(r"([.!?])[ \t]+", "\\1\n", sentence).split("\n") if (p := normal(x))]


KNOWN = {pieces(s)[0]: k for k, s in SENTENCES.items()}
assert all(len(pieces(s)) == 1 for s in SENTENCES.values())


#: A known sentence between ends of sentences or lines, its words parted by blanks or line breaks; longer ones are tried first.
FOUND = r"(?<![^\n\r])(?:" + "|".join(k.replace(" ", "[ \\n]") for k in sorted(KNOWN, key=len, reverse=True)) + r")(?![^\n\r])"


def sentence_ids(text: Column) -> Column:
    """Identifiers of the known sentences of a text, wrapped or not, in order of appearance; unknown sentences are passed over.

    Line breaks become \\n and may part the words of a sentence; ends of sentences become \\r and may not.
    """
    lines = F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[\r\n]+", "\n")
    ended = F.regexp_replace(lines, r"([.!?])[ \t]+", "$1\r")
    plain = F.regexp_replace(F.regexp_replace(ended, r"[^\p{L}\p{N}\n\r]+", " "), r" *\r[ \n\r]*", "\r")
    tidy = F.trim(F.regexp_replace(plain, r" *\n[ \n]*", "\n"))
    table = F.create_map(*[F.lit(x) for pair in KNOWN.items() for x in pair])
    return F.transform(F.regexp_extract_all(tidy, F.lit(FOUND), F.lit(0)), lambda s: F.element_at(table, F.translate(s, "\n", " ")))


def license_scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, n_known, sentence_ids, licenses, families.

    sentence_ids, licenses and families are comma-separated strings, empty where nothing is found; licenses go by rule
    order, families by name. A null text counts as empty. Repeated rows give repeated rows; other columns are ignored.
    """
    out = docs.select(F.col(id_col).alias(id_col), sentence_ids(F.col(text_col)).alias("ids"))
    out = out.select(id_col, "ids", F.concat_ws("", F.transform("ids", lambda i: F.concat(F.lit("<"), i, F.lit(">")))).alias("rest"), F.array().cast("array<string>").alias("names"), F.array().cast("array<string>").alias("kinds"))
    for name, family, ids in RULES:
        mark = "".join(f"<{i}>" for i in ids)
        hit = F.contains("rest", F.lit(mark))
        add = lambda to, what: F.when(hit, F.array_append(to, F.lit(what))).otherwise(F.col(to))  # noqa: B023, E731
        out = out.select(id_col, "ids", F.replace("rest", F.lit(mark), F.lit("<>")).alias("rest"), add("names", name).alias("names"), add("kinds", family).alias("kinds"))
    return out.select(id_col, F.size("ids").cast("long").alias("n_known"), F.concat_ws(",", "ids").alias("sentence_ids"), F.concat_ws(",", "names").alias("licenses"), F.concat_ws(",", F.sort_array(F.array_distinct("kinds"))).alias("families"))
