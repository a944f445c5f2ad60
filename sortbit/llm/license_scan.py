"""License scan by digests of canonical text.

Two texts that differ only in case, punctuation, white space, copyright lines, list
marks or the spelling of some words have one canonical form; its SHA-256 is looked up in
the digests of known licenses and notices by a hash join. Two kinds of text are looked up:
each document as a whole, and each of its lines that has a word, as notices of one line
stand inside other text. The known texts are a parameter; `KNOWN` holds notices and, from
`license_texts`, whole licenses with their usual titles and variants.

All steps are DataFrame operations. Null texts have no digest and no license. A text
without a word (also one whose lines are all copyright lines) has the digest of the empty
form, which no known text may have. Equal known forms under two names give both names.
"""

from __future__ import annotations

import re
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import keep

#: Known texts beyond this many bytes are joined by a shuffle instead of a broadcast.
BROADCAST_BYTES = 8 << 20

# Spellings that count as one, and typographic signs that count as punctuation.
SPELLINGS = [
    ("licence", "license"),
    ("licenced", "licensed"),
    ("sublicence", "sublicense"),
    ("acknowledgement", "acknowledgment"),
    ("analogue", "analog"),
    ("favour", "favor"),
    ("judgement", "judgment"),
    ("merchantibility", "merchantability"),
    ("organisation", "organization"),
    ("whilst", "while"),
]
SIGNS = "‘’“”–—…©\u00a0"

#: A line that opens with a copyright statement.
COPYRIGHT_LINE = r"(^|\n)[^a-z0-9\n]*(copyright|\(c\)|©|all rights reserved)[^\n]*"
#: Signs, and ASCII that is neither letter nor digit.
PLAIN_GAP = rf"[\x00-\x2F\x3A-\x60\x7B-\x7F{SIGNS}]+"

#: License name and a text under which it is known.
KNOWN = [
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License");'),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "Licensed under the GNU General Public License, version 3."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
    (
        "ISC",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, "
        "provided that the above copyright notice and this permission notice appear in all copies.\n"
        'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED '
        "WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR "
        "CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, "
        "NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    ),
    (
        "MIT",
        "MIT License\nPermission is hereby granted, free of charge, to any person obtaining a copy of this software and associated "
        'documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to '
        "use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the "
        "Software is furnished to do so, subject to the following conditions:\nThe above copyright notice and this permission notice "
        'shall be included in all copies or substantial portions of the Software.\nTHE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF '
        "ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE "
        "AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, "
        "WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER "
        "DEALINGS IN THE SOFTWARE.",
    ),
]

_MIT, _ISC = ((n, t.split("\n", 1)[1]) if n == "MIT" else (n, t) for n, t in reversed(KNOWN[-2:]))
#: Titles a text may bear, besides none.
TITLES = {
    "MIT": ["MIT License", "The MIT License", "The MIT License (MIT)", "MIT", "MIT License (MIT)", "Expat License"],
    "ISC": ["ISC License", "The ISC License", "ISC License (ISC)", "ISC"],
    "BSD-2-Clause": ["BSD 2-Clause License", "The BSD 2-Clause License", "The 2-Clause BSD License", "BSD-2-Clause", 'BSD 2-Clause "Simplified" License', "Simplified BSD License", "FreeBSD License", "BSD License"],
    "BSD-3-Clause": ["BSD 3-Clause License", "The BSD 3-Clause License", "The 3-Clause BSD License", "BSD-3-Clause", 'BSD 3-Clause "New" or "Revised" License', "New BSD License", "Modified BSD License", "BSD License", "The BSD License"],
    "Unlicense": ["The Unlicense", "Unlicense"],
}
#: Wordings in use beside the one in the text.
WORDINGS = {
    "BSD-2-Clause": [("IN NO EVENT SHALL THE COPYRIGHT HOLDER", "IN NO EVENT SHALL THE COPYRIGHT OWNER"), ("IN NO EVENT SHALL THE COPYRIGHT HOLDER", "IN NO EVENT SHALL THE COPYRIGHT HOLDERS"), ("\n1. ", "\n* "), ("\n2. ", "\n* ")],
    "BSD-3-Clause": [("IN NO EVENT SHALL THE COPYRIGHT HOLDER", "IN NO EVENT SHALL THE COPYRIGHT OWNER"), ("IN NO EVENT SHALL THE COPYRIGHT HOLDER", "IN NO EVENT SHALL THE COPYRIGHT HOLDERS"), ("name of the copyright holder", "name of the <organization>"), ("name of the copyright holder", "name of copyright holder"), ("name of the copyright holder nor the names of its", "names of the copyright holders nor the names of the"), ("name of the copyright holder nor the names of its", "name of the author nor the names of its")],
    "Unlicense": [("https://unlicense.org", "http://unlicense.org/")],
}


def _form(text: str) -> str:
    """Close to `canonical`, without spellings: only to leave out variants that are equal anyway."""
    return re.sub(PLAIN_GAP, " ", re.sub(COPYRIGHT_LINE, r"\1", text.lower())).strip()


def _variants(name: str, text: str) -> list[str]:
    """The text as it is known: by its wordings, with and without what follows the terms, wrapped or not, under its titles."""
    every = [text]
    for old, new in WORDINGS.get(name, []) + [("https://", "http://"), ("http://", "https://")]:
        every += [t.replace(old, new) for t in every if old in t]
    if name.startswith("BSD"):
        every += [re.sub(r"(?m)^ *\d\. ", "* ", t) for t in every]
    end = "END OF TERMS AND CONDITIONS"
    every += [t[: t.index(end) + len(end)] for t in every if end in t] + [t[: t.index(end)] for t in every if end in t]
    every += [re.sub(r"(?<=\S)[ \t]*\n[ \t]*(?=\S)", " ", t) for t in every]  # a wrapped line may open with the word copyright
    every += [f"{title}\n\n{t}" for title in TITLES.get(name, []) for t in every]
    return list({_form(t): t for t in every}.values())


def _whole_texts() -> list[tuple[str, str]]:
    files = sorted((Path(__file__).parent / "license_texts").glob("*.txt"))
    texts = [_MIT, _ISC] + [(re.sub(r"\.(regents\.)?txt$", "", f.name), f.read_text(encoding="utf-8")) for f in files]
    return [(name, t) for name, text in texts for t in _variants(name, text)]


KNOWN += _whole_texts()


def canonical(text: Column) -> Column:
    """The form under which texts count as equal: plain lower-case words, one blank before and after each."""
    x = F.regexp_replace(F.lower(text), COPYRIGHT_LINE, "$1")
    x = F.concat(F.lit(" "), F.trim(F.regexp_replace(x, PLAIN_GAP, " ")), F.lit(" "))
    # bound to a name, so that the guard and the replacements share one value
    return F.trim(F.element_at(F.transform(F.array(x), lambda y: F.when(y.rlike(_SPELLED), _respelled(y)).otherwise(y)), 1))


_SPELLED = f" (?:{'|'.join(old for old, _ in SPELLINGS)}) "


def _respelled(x: Column) -> Column:
    for old, new in SPELLINGS:
        old, new = F.lit(f" {old} "), F.lit(f" {new} ")
        x = F.replace(F.replace(x, old, new), old, new)  # twice, as neighbours share a blank
    return x


def digest(text: Column) -> Column:
    return F.sha2(canonical(text), 256)


def known_texts(spark: SparkSession, known: list[tuple[str, str]] = KNOWN) -> DataFrame:
    return spark.createDataFrame(known, "license string, text string")


def scan(docs: DataFrame, known: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, digest, license, notices) for every row: the whole text's license, and those of its lines, sorted, joined by commas.

    known: license, text. Both are null where nothing is known.
    """
    names = known.where(canonical(F.col("text")) != "").select(digest(F.col("text")).alias("digest"), "license").distinct()
    names = names.groupBy("digest").agg(F.array_join(F.sort_array(F.collect_set("license")), ",").alias("license"))
    names = keep(names)
    size = names.agg(F.sum(F.length("license") + 96)).first()[0] or 0
    names = F.broadcast(names) if size <= BROADCAST_BYTES else names
    docs = docs.select(F.col(id_col).alias("id"), "text")
    whole = docs.select("id", digest(F.col("text")).alias("digest")).join(names, "digest", "left")
    lines = docs.select("id", F.explode(F.split("text", "\n")).alias("line"))
    found = lines.select("id", digest(F.col("line")).alias("digest")).join(names, "digest")
    notices = found.select("id", F.explode(F.split("license", ",")).alias("license")).groupBy("id").agg(F.array_join(F.sort_array(F.collect_set("license")), ",").alias("notices"))
    return whole.join(notices, "id", "left").select(F.col("id").alias(id_col), "digest", "license", "notices")
