"""Whole documents that are a common license, as op2_license_scan gets them."""

import textwrap
from pathlib import Path

import pyspark
from sortbit.llm import license_scan

TEXTS = Path(license_scan.__file__).parent / "license_texts"
MIT = dict((n, t) for n, t in license_scan.KNOWN if "Permission is hereby granted, free" in t and n == "MIT")["MIT"]


def test_whole_licenses(spark):
    cases = []
    for f in sorted(TEXTS.glob("*.txt")):
        name, text = f.name.removesuffix(".txt").removesuffix(".regents"), f.read_text(encoding="utf-8")
        cases += [(name, text), (name, "Copyright (c) 2019 Some One\n\n" + text.upper())]
    body = MIT[MIT.index("Permission is hereby") :]
    cases += [("MIT", f"{head}\n\nCopyright (c) 2020 A. Body\n\n{body}") for head in ("", "MIT License", "The MIT License", "The MIT License (MIT)")]
    bsd = (TEXTS / "BSD-3-Clause.txt").read_text(encoding="utf-8")
    cases += [("BSD-3-Clause", "BSD 3-Clause License\n\nCopyright (c) 2001, X\nAll rights reserved.\n\n" + bsd.replace("\n3. ", "\n* ").replace("\n2. ", "\n* ").replace("\n1. ", "\n* "))]
    cases += [("BSD-3-Clause", "\n".join(textwrap.fill(x, 300) for x in bsd.split("\n")))]
    gpl = (TEXTS / "GPL-3.0.txt").read_text(encoding="utf-8")
    cases += [("GPL-3.0", gpl[: gpl.index("END OF TERMS AND CONDITIONS") + 27]), ("GPL-3.0", gpl.replace("https://", "http://"))]
    held = Path(pyspark.__file__).parent / "licenses"  # as others ship them
    cases += [(n, (held / f).read_text()) for n, f in (("MIT", "LICENSE-bootstrap.txt"), ("CC0-1.0", "LICENSE-CC0.txt"), ("ISC", "LICENSE-d3.min.js.txt")) if (held / f).exists()]
    cases += [(None, gpl + "\nand more terms"), (None, bsd.replace("without modification", "with changes"))]
    df = spark.createDataFrame([(i, t) for i, (_, t) in enumerate(cases)], "doc_id long, text string")
    got = {x.doc_id: x.license for x in license_scan.scan(df, license_scan.known_texts(spark)).collect()}
    assert [(i, got[i]) for i in range(len(cases))] == [(i, n) for i, (n, _) in enumerate(cases)]
    assert {n for n, _ in cases} >= {"Apache-2.0", "BSD-2-Clause", "BSD-3-Clause", "GPL-2.0", "GPL-3.0", "LGPL-2.1", "LGPL-3.0", "MPL-2.0", "Unlicense", "MIT", "ISC"}
