"""Licence scans over vectors of whole texts and header blocks."""

import pathlib

import duckdb
import pytest
from pyspark.sql import functions as F

from orderless.llm import catalog, license_texts

FOLDER = pathlib.Path(license_texts.__file__).parent / "licence_texts"
FILLER = ["plain words about rivers and stones", "another text of the harbour", "one more line on bread and salt"]


@pytest.mark.parametrize("more", [3, 3000])
def test_licence_files_and_headers(spark, more):
    mit, bsd = (FOLDER / "MIT.txt").read_text(), (FOLDER / "BSD-3-Clause.txt").read_text()
    body = "\n\n" + "\n".join(FILLER * 40)
    head = "\n".join("# " + x for x in ["Copyright (c) 2015 Some One", *bsd.split("\n")[2:]])
    rows = [
        ("m/LICENSE", mit.replace("Permission", "Copyright (c) 2015 Some One\n\nPermission", 1)),
        ("m/src/x", "no notice here"),
        ("g/COPYING", (FOLDER / "GPL-3.0.txt").read_text()),
        ("g/y", "nothing here either"),
        ("h/file.py", head + body),
        ("h/z", "none at all"),
        ("c/a", "Copyright 2019 The Authors. All rights reserved." + body),
        ("c/b", "Copyright (c) 2019-2021 Some Long Company Ltd. All rights reserved." + body),
        ("c/c", None),
    ]
    rows = [(i, p, t) for i, (p, t) in enumerate(rows)] + [(100 + i, "f/x", FILLER[i % 3] + f" {i}") for i in range(more)]
    got = {r.path: r for r in license_texts.license_scan(spark.createDataFrame(rows, "doc_id long, where string, text string"), F.col("where")).collect()}
    told = {p: (r.license, r.origin) for p, r in got.items()}
    assert told["m/LICENSE"] == ("MIT", "notice") and told["m/src/x"] == ("MIT", "inherited") and got["m/src/x"].licence_dir == "m"
    assert told["g/COPYING"] == ("GPL-3.0", "notice") and told["g/y"] == ("GPL-3.0", "inherited")
    assert told["h/file.py"] == ("BSD-3-Clause", "notice") and got["h/file.py"].part == "head" and got["h/file.py"].similarity > 0.9 and told["h/z"] == (None, "none")
    assert told["c/a"] == told["c/b"] == ("proprietary", "notice") and told["c/c"] == told["f/x"] == (None, "none")


def test_license_texts_oracle(spark, sf):
    c = duckdb.connect()
    c.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    df = catalog.queries()["op4_license_texts"](spark, sf)
    r = c.sql(catalog.oracle_sql()["op4_license_texts"])
    at = [r.columns.index(x) for x in df.columns]
    same = lambda rows: sorted((tuple(round(v, 5) if isinstance(v, float) else v for v in x) for x in rows), key=repr)
    assert same(map(tuple, df.collect())) == same(tuple(x[i] for i in at) for x in r.fetchall())
