"""Licence texts in other forms, and what the digest index leaves behind."""

import re
import textwrap

from pyspark.sql import functions as F

from subwin.llm import exact_dedup, license_scan
from subwin.storage import Scratch


def test_forms_of_every_known_text(spark):
    """Wrapped, in capitals, with other copyright statements and spellings, each known text is still itself."""
    rows, want = [], {}
    for name, text in license_scan.KNOWN:
        wrapped = "\n".join(textwrap.fill(line, 61) for line in text.split("\n"))
        spelt = re.sub(r"\b([Ll])icense\b", r"\1icence", wrapped).replace("sublicense", "sub-license").replace("copyright holder", "copyright owner").replace('"', "”").replace("-", "—")
        dated = "/* Copyright 1999-2024, The Authors; all rights reserved */\n(c) 2020 Jane Doe <jane@example.org>\n" + wrapped.replace("Copyright (c) holders\n", "© Jane Doe\n")
        for form in (text, wrapped, text.upper(), spelt, dated, f"Copyright (c) 2024 Jane Doe. {text}" if text.startswith(("Licensed", "This ")) else text):
            want[len(rows)] = name
            rows.append((len(rows), form))
        rows.append((len(rows), text + " except on Sundays"))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {x.doc_id: x.license_id for x in license_scan.scan_licenses(docs, license_scan.known_digests(spark)).collect()}
    assert got == {i: want.get(i) for i, _ in rows}


def test_statements(spark):
    """A licence's own sentence about the copyright notice stays, wherever its lines break."""
    forms = ["copyright notice and this\npermission notice", "copyright 2020 some one\nrest", "the copyright\n(c) me\nrest", "copyright", "Copyright holders keep all"]
    rows = spark.createDataFrame([(x,) for x in forms], "text string").select(license_scan.canonical(F.col("text")).alias("form")).collect()
    assert [x.form for x in rows] == ["copyright notice and this permission notice", "rest", "the copyright rest", "copyright", "copyright holders keep all"]


def test_index_leaves_nothing_and_compacts(spark):
    docs = spark.createDataFrame([(i, f"text {i % 7}") for i in range(50)] + [(50, None), (None, "text 1")], "doc_id long, text string")
    before = {t.name for t in spark.catalog.listTables()}
    assert exact_dedup.ingest_once(docs).where("kept").count() == 8
    assert exact_dedup.drop_copies(docs).count() == 8
    assert {t.name for t in spark.catalog.listTables()} == before
    root = Scratch(spark, "test").root
    index = exact_dedup.DigestIndex(spark, f"{root}/a", 3)
    for i in range(3):
        index.ingest(docs.selectExpr("doc_id", f"concat(text, doc_id % {i + 2}) AS text")).count()
    rows, files = sorted(map(tuple, index.rows().collect())), len(index.rows().inputFiles())
    index.compact(f"{root}/b")
    assert sorted(map(tuple, index.rows().collect())) == rows and len(index.rows().inputFiles()) <= 3 < files
    assert index.ingest(docs.selectExpr("doc_id", "concat(text, doc_id % 2) AS text")).where("kept").count() == 0
    index.ingest(docs.selectExpr("doc_id", "concat('new ', text) AS text")).count()
    assert index.rows().count() > len(rows)
    index.close()
    assert {t.name for t in spark.catalog.listTables()} == before
