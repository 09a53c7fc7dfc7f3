import re
import textwrap

import pytest

from predtopics.llm import licenses as li

GIVEN = {
    "Released under the MIT License.": "MIT", "Licensed under the Apache License, Version 2.0.": "Apache-2.0",
    "This work is licensed under the GNU General Public License, version 3.": "GPL-3.0", "Licensed under CC BY-NC 4.0.": "CC-BY-NC-4.0",
}


@pytest.mark.parametrize("statement,name", [*GIVEN.items(), *((s + ".", n) for n, all_ in li.STATEMENTS.items() for s in all_)])
def test_statements_are_told_apart(statement, name):
    prose = "Thond edat the erbleti, and onhe was in. "
    assert {x["license"] for x in li.scan(prose + statement + "\n" + prose)} == {name}
    assert {x["license"] for x in li.scan(prose * 30 + statement + " " + prose * 30)} == {name}


@pytest.mark.parametrize("text", ["He had a driving license.", "no license is needed to read this", "Licensed under the Apache License, Version 1.1.", "Copyright law is long.", "Licensed under CC BY-XX 9.0.", "", "permission"])
def test_other_uses_of_the_words_are_none(text):
    assert li.scan(text) == []


def test_whole_table(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    got = {r.doc_id: {x["license"] for x in r.found} for r in li.scan_licenses(docs).collect()}
    want = {r.doc_id: {n for s, n in (GIVEN | {"All rights reserved": "Proprietary"}).items() if s in r.text} for r in docs.collect()}
    assert got == want


def test_edges(spark):
    rows = [(1, None), (2, ""), (None, "Released under the MIT License."), (3, "license " * 20_000), (None, "Released under the MIT License.")]
    frame = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as found", "2 as n_blocks")
    got = sorted((r.doc_id or 0, [x["license"] for x in r.found]) for r in li.scan_licenses(frame).collect())
    assert got == [(0, ["MIT"]), (0, ["MIT"]), (1, []), (2, []), (3, [])]
    assert li.scan_licenses(frame.limit(0)).count() == 0
    assert re.search(li.MARKER, "CC BY-NC")


def names(text):
    return {x["license"] for x in li.scan(text)}


def test_every_license_of_a_block_is_told():
    notice = "Copyright 2019 The Authors, all of whom hold the copyright in their own parts of this program and its manual.\nLicensed under the Apache License, Version 2.0 (the \"License\");\nyou may not use this file except in compliance with the License.\n"
    notice += "Unless required by law, the program comes without warranty of any kind.\nReleased under the MIT License\nLicensed under CC BY-NC 4.0"
    assert names(notice) == {"Apache-2.0", "MIT", "CC-BY-NC-4.0"}
    every = [s[0] for s in li.STATEMENTS.values()]
    assert names(". ".join(every) + ".") == names(".\n\n".join(every)) == set(li.STATEMENTS)
    assert names("Licensed under CC BY-NC 4.0 or licensed under the CC BY 4.0") == {"CC-BY-NC-4.0", "CC-BY-4.0"}


@pytest.mark.parametrize("text", ["Copyright 2020 the MIT Press", "Copyright of the Apache server version 2.0", "Copyright, mit der Bitte um permission"])
def test_names_without_a_license_word_are_none(text):
    assert li.scan(text) == []


@pytest.mark.parametrize("name", ["ISC", "BSD-2-Clause", "BSD-3-Clause", "MIT", "Apache-2.0", "GPL-3.0"])
@pytest.mark.parametrize("width", [30, 72])
@pytest.mark.parametrize("mark", ["", "# "])
def test_wrapped_statements_are_whole(name, width, mark):
    for statement in li.STATEMENTS[name]:
        wrapped = "\n".join(mark + x for x in textwrap.wrap(statement, width))
        for text in (wrapped, f"{mark}tool\n{wrapped}\n{mark}Copyright 2020 by its authors", f"Thond edat.\n\n{wrapped}:\r\n\r\nThond edat."):
            assert name in names(text)


def test_a_wrapped_version_is_another_license():
    assert names("This work is licensed under the GNU General Public License,\nversion 2.") == {"GPL-2.0"}
    assert names("Licensed under the Apache License, Version\n1.1.") == names("Licensed under CC\nBY-XX 9.0") == set()


def test_compression_chooses_what_wording_confirms(monkeypatch):
    text = "Thond edat. Released under the MIT License. Thond edat."
    assert names(text) == {"MIT"}
    monkeypatch.setattr(li, "reductions", lambda block: [(0.5, "Apache-2.0"), (0.0, "MIT")])
    assert names(text) == set()  # what saves nothing is not chosen, whatever its wording


@pytest.mark.parametrize("text", ["ALL RIGHTS RESERVED", "RELEASED UNDER THE MIT LICENSE", "license " * 5000 + "Licensed under the ISC License " + "license " * 5000])
def test_no_wording_is_lost_to_case_or_length(text):
    assert len(names(text)) == 1
    assert max(len(s) for t, _ in li._ready() for s in t.statements) + 3 <= li.WINDOW // 2
