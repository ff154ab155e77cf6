"""License scans by sentence rules.

A text is cut into sentences, each normalised (lower case, letters and digits only, single
spaces). A blank line (or one of comment marks alone) and a sentence mark end a sentence; a lone line
end may end one or be a hard wrap: a known sentence is found over any number of wraps, marks of comments
at line starts are blanks, and of sentences that start at one place the longest counts, so one-line
notices between other lines are found too. Known licence sentences map to identifiers; the identifiers found, in order, are matched
against ordered rules: a rule names a licence and the identifiers that must follow one
another (other sentences may stand between them). Rules are tried in their order, each as often as it matches; the
sentences of a match are used up, so a fuller text leaves nothing for the shorter notices that come behind it.

At scale: a narrow projection; the sentence and rule tables are constants. Texts without any
licence word skip the sentence step by a built-in function.

Defined cases: null is empty; a text without known sentences has an empty list; repeated rows are
scanned row by row; an empty table gives an empty table; extra columns are left unread.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from semrank.llm.text import whole

#: Public licence texts, one sentence each, as they are cut (a semicolon or a full stop before a blank ends one).
SENTENCES = {
    "mit-name": "MIT License",
    "mit-the": "The MIT License (MIT)",
    "mit-released": "Released under the MIT License.",
    "mit-under": "Licensed under the MIT License.",
    "mit-grant": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "mit-notice": "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "mit-as-is": "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT.",
    "mit-liable": "IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "apache-name": "Licensed under the Apache License, Version 2.0.",
    "apache-title": "Apache License",
    "apache-copyright": "Subject to the terms and conditions of this License, each Contributor hereby grants to You a perpetual, worldwide, non-exclusive, no-charge, royalty-free, irrevocable copyright license to reproduce, prepare Derivative Works of, publicly display, publicly perform, sublicense, and distribute the Work and such Derivative Works in Source or Object form.",
    "apache-grant": "Licensed under the Apache License, Version 2.0 (the \"License\");",
    "apache-use": "you may not use this file except in compliance with the License.",
    "apache-obtain": "You may obtain a copy of the License at",
    "apache-unless": "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    "apache-see": "See the License for the specific language governing permissions and limitations under the License.",
    "gpl3-work": "This work is licensed under the GNU General Public License, version 3.",
    "gpl-free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "gpl-hope": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY;",
    "gpl-implied": "without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.",
    "gpl-details": "See the GNU General Public License for more details.",
    "gnu-program": "This program is free software;",
    "gnu-library": "This library is free software;",
    "gpl-terms": "you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation;",
    "gpl2-terms": "you can redistribute it and/or modify it under the terms of the GNU General Public License version 2 as published by the Free Software Foundation.",
    "gnu-later-2": "either version 2 of the License, or (at your option) any later version.",
    "gnu-later-2-1": "either version 2.1 of the License, or (at your option) any later version.",
    "gnu-later-3": "either version 3 of the License, or (at your option) any later version.",
    "lgpl-terms": "you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation;",
    "lgpl-free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "lgpl-hope": "This library is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY;",
    "agpl-free": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "agpl-details": "See the GNU Affero General Public License for more details.",
    "mpl-form": "This Source Code Form is subject to the terms of the Mozilla Public License, v",
    "isc-name": "ISC License",
    "isc-grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "isc-as-is": "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS.",
    "cc-by-nc-4": "Licensed under CC BY-NC 4.0.",
    "cc-by-4": "Licensed under CC BY 4.0.",
    "cc-by-sa-4": "Licensed under CC BY-SA 4.0.",
    "cc-by-work": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "cc-by-sa-work": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "cc-by-nc-work": "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
    "bsd-grant": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "bsd-source": "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "bsd-binary": "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "bsd-endorse": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    "bsd-as-is": "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED.",
    "unlicense": "This is free and unencumbered software released into the public domain.",
    "zlib-as-is": "This software is provided 'as-is', without any express or implied warranty.",
    "zlib-grant": "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:",
    "boost-grant": "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the \"Software\") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following:",
}
#: Ordered: licence, then the identifiers it needs. Fuller texts come before notices, notices before single lines.
RULES = (
    ("MIT", ("mit-grant", "mit-notice", "mit-as-is", "mit-liable")),
    ("MIT", ("mit-grant", "mit-notice")),
    ("MIT", ("mit-name", "mit-grant")),
    ("MIT", ("mit-the", "mit-grant")),
    ("Apache-2.0", ("apache-title", "apache-copyright")),
    ("Apache-2.0", ("apache-grant", "apache-use", "apache-obtain", "apache-unless", "apache-see")),
    ("Apache-2.0", ("apache-grant", "apache-use")),
    ("AGPL-3.0-or-later", ("agpl-free", "gpl-hope", "gpl-implied", "agpl-details")),
    ("AGPL-3.0-or-later", ("agpl-free",)),
    ("LGPL-2.1-or-later", ("gnu-library", "lgpl-terms", "gnu-later-2-1")),
    ("LGPL-3.0-or-later", ("gnu-library", "lgpl-terms", "gnu-later-3")),
    ("LGPL-3.0-or-later", ("lgpl-free",)),
    ("GPL-3.0-or-later", ("gpl-free", "gpl-hope")),
    ("GPL-2.0-or-later", ("gnu-program", "gpl-terms", "gnu-later-2")),
    ("GPL-3.0-or-later", ("gnu-program", "gpl-terms", "gnu-later-3")),
    ("GPL-2.0-only", ("gnu-program", "gpl2-terms")),
    ("BSD-3-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-endorse", "bsd-as-is")),
    ("BSD-3-Clause", ("bsd-grant", "bsd-endorse")),
    ("BSD-2-Clause", ("bsd-grant", "bsd-source", "bsd-binary", "bsd-as-is")),
    ("BSD-2-Clause", ("bsd-grant",)),
    ("MPL-2.0", ("mpl-form",)),
    ("ISC", ("isc-grant", "isc-as-is")),
    ("ISC", ("isc-grant",)),
    ("Zlib", ("zlib-as-is", "zlib-grant")),
    ("BSL-1.0", ("boost-grant",)),
    ("Unlicense", ("unlicense",)),
    ("GPL-3.0-or-later", ("gpl-free",)),
    ("GPL-3.0-only", ("gpl3-work",)),
    ("Apache-2.0", ("apache-name",)),
    ("Apache-2.0", ("apache-grant",)),
    ("MIT", ("mit-released",)),
    ("MIT", ("mit-under",)),
    ("MIT", ("mit-grant",)),
    ("CC-BY-NC-4.0", ("cc-by-nc-work",)),
    ("CC-BY-SA-4.0", ("cc-by-sa-work",)),
    ("CC-BY-4.0", ("cc-by-work",)),
    ("CC-BY-NC-4.0", ("cc-by-nc-4",)),
    ("CC-BY-SA-4.0", ("cc-by-sa-4",)),
    ("CC-BY-4.0", ("cc-by-4",)),
)
#: One of these, which no line end can split, is in every known sentence, in lower case.
WORDS = ("licens", "permission", "software", "program", "redistribut", "warrant")
#: Marks in a normalised text: a line end within a paragraph, a sure end of a sentence.
LINE, STOP = "\u0001", "\u0002"


def normal_text(s: str) -> str:
    return " ".join("".join(c if c in "abcdefghijklmnopqrstuvwxyz0123456789" else " " for c in s.lower()).split())


def marked(text: Column) -> Column:
    """The text normalised, with LINE and STOP where a sentence may and must end."""
    t = F.concat(F.lit("\n"), F.lower(F.translate(text, "\r" + STOP, "  ")), F.lit("\n"))
    t = F.regexp_replace(t, "\n[^a-z0-9]*\n", STOP + "\n")
    t = F.regexp_replace(t, "\n[^a-z0-9\n]*", "\n")
    t = F.translate(F.regexp_replace(t, "[.!?;][ \n]", STOP), "\n", LINE)
    t = F.regexp_replace(t, f"[^a-z0-9{LINE}{STOP}]+", " ")
    return F.concat(F.lit(STOP), F.regexp_replace(t, f" ?([{LINE}{STOP}]) ?", "$1"), F.lit(STOP))


def known_sentences(text: Column) -> Column:
    """The known sentences of a text, normalised, in order of place."""
    longest_first = sorted(map(normal_text, SENTENCES.values()), key=lambda x: (-len(x), x))
    any_of = "|".join(x.replace(" ", f"[ {LINE}]+") for x in longest_first)
    found = F.regexp_extract_all(marked(text), F.lit(f"(?<=[{LINE}{STOP}])({any_of})(?=[{LINE}{STOP}])"), F.lit(1))
    return F.transform(found, lambda x: F.regexp_replace(x, f"[ {LINE}]+", " "))


def known() -> Column:
    """Normalised sentence -> identifier."""
    pairs = [x for k, s in SENTENCES.items() for x in (F.lit(normal_text(s)), F.lit(k))]
    return F.create_map(*pairs)


def match_rules(ids: list[str]) -> list[str]:
    """Licences in rule order; the sentences of a match are used up, other sentences may stand between them."""
    left, out = list(ids), []
    for name, need in RULES:
        while True:
            places, at = [], 0
            for want in need:
                while at < len(left) and left[at] != want:
                    at += 1
                if at == len(left):
                    break
                places.append(at)
                at += 1
            if len(places) < len(need):
                break
            left = [x for i, x in enumerate(left) if i not in places]
            if name not in out:
                out.append(name)
    return out


@F.pandas_udf(T.StringType())
def matched(sequences: pd.Series) -> pd.Series:
    return pd.Series(["" if s is None else ",".join(match_rules(list(s))) for s in sequences], dtype=object)


def license_scan(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_sentences (that are known), sentence_ids in order of place, licenses in order of rule."""
    low = F.lower("_t")
    may = F.lit(False)
    for w in WORDS:
        may = may | low.contains(w)
    d = docs.select(F.col(doc_id).alias("doc_id"), whole(text).alias("_t"))
    d = d.select("doc_id", F.when(may, known_sentences(F.col("_t"))).otherwise(F.array().cast("array<string>")).alias("_k"))
    table = known()
    d = d.select("doc_id", F.transform("_k", lambda x: F.element_at(table, x)).alias("_ids"))
    d = d.select("doc_id", F.size("_ids").cast("bigint").alias("n_sentences"), F.array_join("_ids", ",").alias("sentence_ids"), matched(F.when(F.size("_ids") > 0, F.col("_ids"))).alias("licenses"))
    return d
