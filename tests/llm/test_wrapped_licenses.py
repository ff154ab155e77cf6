"""Licence texts as they are found: hard-wrapped, in comments, beside one-line notices."""

import textwrap

import pytest

from semrank.llm import license_scan

S = license_scan.SENTENCES
MIT = ["MIT License", "Copyright (c) 2020 Some Body", S["mit-grant"], S["mit-notice"], "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND."]
BSD2 = ["Copyright (c) 2020, Some Body\nAll rights reserved.", S["bsd-grant"], "1. Redistributions of source code must retain the above copyright notice.", "2. Redistributions in binary form must reproduce the above copyright notice."]
BSD = [*BSD2, "3. " + S["bsd-endorse"]]
GPL = ["Some program.  Copyright (C) 2020  Some Body", S["gpl-free"], S["gpl-hope"] + " without even the implied warranty of MERCHANTABILITY."]
APACHE = ["Copyright 2020 Some Body", S["apache-grant"] + "\n" + S["apache-use"]]
TEXTS = {"MIT": MIT, "BSD-3-Clause": BSD, "BSD-2-Clause": BSD2, "GPL-3.0-or-later": GPL, "Apache-2.0": APACHE}
IDS = {"MIT": "mit-name,mit-grant,mit-notice", "BSD-3-Clause": "bsd-grant,bsd-endorse", "BSD-2-Clause": "bsd-grant", "GPL-3.0-or-later": "gpl-free,gpl-hope", "Apache-2.0": "apache-grant,apache-use"}


def scanned(spark, texts):
    rows = license_scan.license_scan(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")).collect()
    return [(r.sentence_ids, r.licenses) for r in sorted(rows, key=lambda r: r.doc_id)]


@pytest.mark.parametrize("end", ["\n", "\r\n"])
@pytest.mark.parametrize("first, mark, last", [("", "", ""), ("/*", " * ", " */"), ("", "# ", ""), ("", "// ", ""), ("", ";; ", ""), ("<!--", "  ", "-->")])
def test_wrapped_texts(spark, first, mark, last, end):
    texts, want = [], []
    for name, parts in TEXTS.items():
        for width in (40, 70, 80):
            lines = "\n\n".join(textwrap.fill(p, width) for p in parts).split("\n")
            texts.append(end.join([first, *((mark + x).rstrip() for x in lines), last, "int x = 1;"]))
            want.append((IDS[name], name))
    assert scanned(spark, texts) == want


def test_lines_within_a_paragraph(spark):
    s = S["mit-released"]
    grant = textwrap.fill(S["mit-grant"], 72)
    texts = [
        f"A line of prose\n{s}\nand another one", f"{s}\n{s}", "It is under the MIT\nLicense", "Released under\n\nthe MIT License.",
        f"Copyright 2020 Some Body\n{grant}\nno more", "Licensed under the Apache License,\nVersion 2.0\n(the \"License\");", "Licensed under the Apache\nLicense, Version 2.0.\nOther words",
        "Licensed under CC\nBY-NC 4.0. Licensed under\nCC BY 4.0.", "Released. under the MIT License.", "a" + s, "released under the mit licenses",
    ]
    assert [x for x, _ in scanned(spark, texts)] == ["mit-released", "mit-released,mit-released", "", "", "mit-grant", "apache-grant", "apache-name", "cc-by-nc-4,cc-by-4", "", "", ""]


FULL = {
    "MIT": ["mit-name", "mit-grant", "mit-notice", "mit-as-is", "mit-liable"],
    "Apache-2.0": ["apache-grant", "apache-use", "apache-obtain", "apache-unless", "apache-see"],
    "LGPL-2.1-or-later": ["gnu-library", "lgpl-terms", "gnu-later-2-1", "lgpl-hope", "gpl-implied"],
    "LGPL-3.0-or-later": ["lgpl-free"],
    "AGPL-3.0-or-later": ["agpl-free", "gpl-hope", "gpl-implied", "agpl-details"],
    "GPL-2.0-or-later": ["gnu-program", "gpl-terms", "gnu-later-2", "gpl-hope", "gpl-implied", "gpl-details"],
    "GPL-2.0-only": ["gnu-program", "gpl2-terms"],
    "BSD-3-Clause": ["bsd-grant", "bsd-source", "bsd-binary", "bsd-endorse", "bsd-as-is"],
    "BSD-2-Clause": ["bsd-grant", "bsd-source", "bsd-binary", "bsd-as-is"],
    "MPL-2.0": ["mpl-form"],
    "ISC": ["isc-name", "isc-grant", "isc-as-is"],
    "Zlib": ["zlib-as-is", "zlib-grant"],
    "BSL-1.0": ["boost-grant"],
    "Unlicense": ["unlicense"],
}


def test_full_texts(spark):
    names, texts = [], []
    for name, ids in FULL.items():
        for width in (30, 76):
            names.append(name)
            texts.append("int x;\n\n" + textwrap.fill(" ".join(S[i] if S[i][-1] in ".;" else S[i] + "." for i in ids), width) + "\n\nint y;")
    got = scanned(spark, texts)
    assert [(g[0].split(","), g[1]) for g in got] == [(FULL[n], n) for n in names]


def test_every_known_sentence_passes_the_word_filter(spark):
    assert all(any(w in x.lower() for w in license_scan.WORDS) for x in S.values())
    got = scanned(spark, ["# " + textwrap.fill(x, 20).replace("\n", "\n# ") for x in S.values()])
    assert [g[0] for g in got] == list(S)
    used = {i for _, need in license_scan.RULES for i in need}
    assert used <= set(S)


def test_rules_against_a_plain_matcher():
    """Every rule alone gives its licence unless one before it takes all its sentences."""
    for name, need in license_scan.RULES:
        assert license_scan.match_rules(list(need))[0] in {n for n, _ in license_scan.RULES} and name in license_scan.match_rules([x for i in need for x in (i, "other")])
