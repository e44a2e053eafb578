"""Licences of whole texts, of headers over several lines, of lines that match no template, and of rows of any id."""

import pytest

from slicelink.llm import licenses

PATHS = "doc_id long, path string, text string"
MIT = licenses.TEMPLATES["MIT"][3]
FULL_MIT = "MIT License\n\nCopyright (c) 2020 Some One\n\n" + MIT.replace(": The", ":\n\nThe").replace("SOFTWARE IS", "SOFTWARE\nIS").replace(" Software. THE", " Software.\n\nTHE")
FILLER = [(1000 + i, f"z/{i}.txt", f"word{i} of some text\nwith a line more\n" + " ".join(f"t{i}x{k}" for k in range(30))) for i in range(40)]


def scanned(spark, rows):
    return sorted(((r.doc_id, r.license, r.basis) for r in licenses.scan(spark.createDataFrame(rows + FILLER, PATHS)).collect() if r.doc_id is None or r.doc_id < 1000), key=repr)


@pytest.mark.parametrize("text, want", [
    (FULL_MIT, "MIT"), (licenses.TEMPLATES["ISC"][2], "ISC"), (licenses.TEMPLATES["BSD-2-Clause"][2], "BSD-2-Clause"), (licenses.TEMPLATES["BSD-3-Clause"][3], "BSD-3-Clause"),
    ("                GNU GENERAL PUBLIC LICENSE\n                   Version 2, June 1991\n\n Everyone is permitted to copy and distribute verbatim copies\n of this license document, but changing it is not allowed.", "GPL-2.0"),
    ("                GNU GENERAL PUBLIC LICENSE\n                   Version 3, 29 June 2007\n\n Copyright (C) 2007 Free Software Foundation, Inc.", "GPL-3.0"),
    ("                                 Apache License\n                           Version 2.0, January 2004\n                        http://www.apache.org/licenses/\n\n   TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION", "Apache-2.0"),
])
def test_licence_files_pass_their_licence_on(spark, text, want):
    assert scanned(spark, [(1, "a/LICENSE", text), (2, "a/b/c.txt", "no word of it")]) == [(1, want, "header"), (2, want, "directory")]


def test_headers_over_lines_and_unknown_licences(spark):
    header = "# Copyright 2020 The Authors\n# Permission is hereby granted, free of charge, to any person obtaining a\n# copy of this software and associated documentation files (the\n# Software), to deal in the Software without restriction, including without\n# limitation the rights to use, copy, modify, merge, publish, distribute,\n# sublicense, and/or sell copies of the Software, and to permit persons to\n# whom the Software is furnished to do so, subject to the following conditions:\n\nx = 1\n"
    rows = [(1, "a/LICENSE", "Released under the MIT License."), (2, "a/x.py", header), (3, "a/y.txt", "Licensed under CC BY-NC 4.0."), (4, "a/z.txt", "prose\nLicensed under the Terms of Use of the Quiet Garden Club.\nprose"), (5, "a/w.txt", "copyright is a long story"), (6, "a/v.txt", "SPDX-License-Identifier: GPL-3.0-or-later")]
    assert scanned(spark, rows) == [(1, "MIT", "header"), (2, "MIT", "header"), (3, "CC-BY-NC-4.0", "header"), (4, "unknown", "header"), (5, "MIT", "directory"), (6, "GPL-3.0", "header")]


def test_rows_of_any_id_and_ties(spark):
    mit, apache = "Released under the MIT License.", "Licensed under the Apache License, Version 2.0."
    rows = [(1, "a/LICENSE", mit), (1, "a/LICENSE", mit), (1, "a/LICENSE", apache), (None, "a/x", None), (None, "b/x", mit), (2, None, apache), (2, None, None), (3, "c/COPYING", apache), (3, "c/LICENSE", mit), (4, "c/d/e", "")]
    want = [(1, "MIT", "header"), (1, "MIT", "header"), (1, "Apache-2.0", "header"), (None, "Apache-2.0", "directory"), (None, "MIT", "header"), (2, "Apache-2.0", "header"), (2, None, "none"), (3, "Apache-2.0", "header"), (3, "MIT", "header"), (4, "Apache-2.0", "directory")]
    assert scanned(spark, rows) == sorted(want, key=repr)


def test_blank_lines_and_very_long_texts(spark):
    assert scanned(spark, [(1, "a/b", "license" + "\n" * 30_000 + "end"), (2, "a/c", "word " * 200_000 + "licence")]) == [(1, None, "none"), (2, None, "none")]


def test_every_template_finds_itself(spark):
    rows = [(i, f"d{i}/f.txt", t) for i, (_, t) in enumerate((k, t) for k, v in licenses.TEMPLATES.items() for t in v)]
    names = [k for k, v in licenses.TEMPLATES.items() for _ in v]
    got = {d: n for d, n, _ in scanned(spark, rows)}
    shared = {i for i, (_, _, t) in enumerate(rows) if not any(c in t.lower() for c in licenses.CUES)}
    assert [got[i] for i in range(len(rows)) if i not in shared] == [n for i, n in enumerate(names) if i not in shared] and not shared
