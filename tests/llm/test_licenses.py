"""Whole licence files in the forms they come in, and the SQL on the same rows."""

import re
import textwrap
from collections import Counter
from pathlib import Path

import duckdb
import pyarrow as pa
import pytest

from gainclust.llm import licenses

TITLES = {"MIT": "The MIT License (MIT)", "ISC": "ISC License", "BSD-2-Clause": "BSD 2-Clause License", "BSD-3-Clause": "BSD 3-Clause License", "Zlib": "zlib License", "BSL-1.0": "Boost Software License", "MIT-0": "MIT No Attribution License"}


def forms(name, text):
    """The text as it is found: wrapped, titled, in capitals, re-spelt, commented."""
    lines = "\n\n".join("\n".join(textwrap.wrap(p, 72)) for p in text.split("\n\n"))
    yield text
    yield lines
    yield f"{TITLES.get(name, 'License')}\n\nCopyright (c) 2001-2024 A. Person and others\nAll rights reserved.\n\n{lines}\n"
    yield f"  {TITLES.get(name, 'The License')}  \r\n\r\n© 2020 B. Company, Inc.\r\n" + lines.replace("\n", "\r\n")
    yield text.upper()
    yield re.sub(r"\b(sub)?license", r"\1licence", text).replace("organization", "organisation")
    yield "\n".join(f" * {x}" for x in f"Copyright 2019 someone\n{lines}".split("\n"))


def test_forms_of_known_texts_equal_sql(spark):
    rows = [(name, x) for name, texts in licenses.KNOWN.items() for text in texts if len(text) > 300 for x in forms(name, text)]
    rows += [(None, "no licence"), (None, licenses.KNOWN["MIT"][0] + "\nand something else"), (None, "Copyright notice and this permission notice appear"), (None, None), (None, "")]
    df = spark.createDataFrame([(i, t, "x") for i, (_, t) in enumerate(rows)], "doc_id long, text string, digest string").repartition(3)
    got = [(r.id, r.digest, r.license_id) for r in licenses.scan(df).collect()]
    assert {i: found for i, _, found in got} == {i: name for i, (name, _) in enumerate(rows)}
    with duckdb.connect() as db:
        db.register("documents", pa.table({"doc_id": pa.array(range(len(rows)), pa.int64()), "text": [t for _, t in rows]}))
        assert Counter(got) == Counter(db.sql(licenses.oracle()).fetchall())


def test_words_of_the_body_are_not_taken_for_notices(spark):
    text = spark.createDataFrame([("copyright notice and this permission notice\ncopyright holders\n(c) the third item\ncopyright 2020 x\ncopyright [yyyy] y\n",)], "t string")
    form = text.select(licenses.canonical(text["t"])).first()[0]
    assert form == "copyright notice and this permission notice copyright holders c the third item"


def test_empty_table(spark):
    assert licenses.scan(spark.createDataFrame([], "doc_id long, text string")).collect() == []


@pytest.mark.skipif(not Path("/usr/share/common-licenses/GPL-3").exists(), reason="no licence texts installed")
def test_known_texts_from_files(spark, tmp_path):
    for name in ("GPL-3", "Apache-2.0", "MPL-2.0"):
        (tmp_path / f"{name}.txt").write_text(Path(f"/usr/share/common-licenses/{name}").read_text())
    whole = (tmp_path / "GPL-3.txt").read_text()
    df = spark.createDataFrame([(1, " ".join(whole.split())), (2, whole + "x"), (3, (tmp_path / "MPL-2.0.txt").read_text().upper())], "doc_id long, text string")
    got = {r.id: r.license_id for r in licenses.scan(df, licenses.known_files(spark, f"file://{tmp_path}")).collect()}
    assert got == {1: "GPL-3", 2: None, 3: "MPL-2.0"}
