"""Whole licence texts, wrapped headers and denials."""

import pytest

from mergecount.llm import licences

MIT = next(t for n, t in licences.TEMPLATES if n == "MIT" and t.startswith("Permission"))


@pytest.fixture(scope="module")
def found(spark):
    whole = {name: text for name, text in licences.templates() if len(text.split()) > licences.LONG}
    wrapped = "# This program is free software: you can redistribute it and/or modify\n# it under the terms of the GNU General Public License as published by\n# the Free Software Foundation, either version 3 of the License, or\n# (at your option) any later version.\n"
    bsd = "/*\n * Redistribution and use in source and binary forms, with or without\n * modification, are permitted provided that the following conditions\n */\n"
    files = [(f"/w{i}/LICENSE", text[: int(len(text) * 0.9)]) for i, text in enumerate(whole.values())]
    files += [(f"/w{i}/src/deep/x.py", "plain code") for i in range(len(whole))]
    files += [
        ("/m/LICENSE", f"The MIT License (MIT)\n\nCopyright (c) 2020 Somebody Else\n\n{MIT}, {licences.MIT_REST}"), ("/m/a.c", "int main;"),
        ("/h/wrapped.py", f"{wrapped}\n\ncode and more code of quite another kind " + "blah " * 300), ("/h/bsd.c", f"{bsd}\n\nint x; " + "word " * 300),
        ("/n/no.txt", "This file is not licensed under the MIT License.\n\n" + "other words here " * 50), ("/n/other.txt", "nothing to see"),
    ]
    rows = licences.scan(spark.createDataFrame(files, "path string, text string")).collect()
    return list(whole), {r["path"]: (r["licence"], r["how"], r["stated_in"]) for r in rows}


def test_whole_texts_state_their_directory(found):
    names, got = found
    for i, name in enumerate(names):
        assert got[f"/w{i}/LICENSE"][0] == name  # by the whole text, or by a notice that the text itself quotes
        assert got[f"/w{i}/src/deep/x.py"] == (name, "directory", f"/w{i}/LICENSE")
    assert got["/m/LICENSE"][0] == "MIT" and got["/m/a.c"] == ("MIT", "directory", "/m/LICENSE")


def test_wrapped_headers(found):
    _, got = found
    assert got["/h/wrapped.py"][:2] == ("GPL-3.0", "header") and got["/h/bsd.c"][:2] == ("BSD-3-Clause", "header")


def test_denials_state_nothing(found):
    _, got = found
    assert got["/n/no.txt"] == (None, None, None) and got["/n/other.txt"] == (None, None, None)
