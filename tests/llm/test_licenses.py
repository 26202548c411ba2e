import random
import re

import pytest

from shardgraph.llm import licenses

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def brute(text):
    words = WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    at = [(k, label) for phrase, label in licenses.BASE.items() for k in range(len(words)) if words[k : k + len(phrase.split())] == phrase.split()]
    places = [k for k, _ in at]
    return len(words), len(at), min(places, default=None), max(places, default=None), ",".join(sorted({x for _, x in at}))


TEXTS = [None, "", "MIT License", "the mit license apache license mit-license.", "mit licenses", "CC BY-NC 4.0 cc by", "GNU  General\nPublic License, gnu general public license", "é mit license é", "mitlicense mit\x7flicense", "permit license", "mit license " * 5000, "１ mit　license"]


@pytest.mark.parametrize("text", TEXTS)
def test_scan_equals_word_search(text):
    assert licenses.scan(text or "", licenses.automaton({licenses.TAG: None} | licenses.NOTICES | licenses.BASE))[:5] == brute(text)


def test_random_texts():
    rng = random.Random(1)
    machine = licenses.automaton({licenses.TAG: None} | licenses.NOTICES | licenses.BASE)
    for _ in range(200):
        t = "".join(rng.choice(["mit", "license", "apache", "cc", "by", "gnu", "general", "public", " ", " ", "-", "\n", "é", "X"]) for _ in range(60))
        assert licenses.scan(t, machine)[:5] == brute(t)


@pytest.mark.parametrize("text,names,freedom", [("MIT", ["mit"], 1.0), ("MIT OR GPL-3.0-only", ["mit", "gpl-3.0"], 1.0), ("MIT AND GPL-2.0+", ["mit", "gpl-2.0"], 0.4), ("(MIT OR Apache-2.0) AND CC-BY-NC-4.0 */", ["mit", "apache-2.0", "cc-by-nc-4.0"], 0.2), ("GPL-2.0-only WITH Classpath-exception-2.0", ["gpl-2.0"], 0.7), ("MIT OR GPL-3.0 AND CC-BY-NC-4.0", ["mit", "gpl-3.0", "cc-by-nc-4.0"], 1.0), ("MIT OR", ["mit"], 1.0), ("MIT and then prose", ["mit", "then"], 0.4)])
def test_expressions(text, names, freedom):
    assert licenses.parse(text) == (names, freedom)


@pytest.mark.parametrize("text", ["", "( MIT", "OR MIT", ") x", "***"])
def test_no_expression(text):
    assert licenses.parse(text) is None


def test_tags_add_labels():
    machine = licenses.automaton({licenses.TAG: None} | licenses.NOTICES | licenses.BASE)
    out = licenses.scan("// SPDX-License-Identifier: Apache-2.0 OR MIT\ncode", machine)
    assert out[5] == "apache-2.0,mit" and out[6] == 1.0 and out[7] == 1.0 and out[4] == ""


def test_whole_table(spark, data):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{data}/documents.parquet").collect()}
    rows = licenses.query(spark, data).collect()
    assert len(rows) == len(docs)
    for r in rows:
        assert tuple(r)[1:6] == brute(docs[r.doc_id]) and 0 <= r.score <= 1
        assert set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(","))


def test_edges(spark):
    df = spark.createDataFrame([(None, t, 1.0) for t in TEXTS] + [(1, "mit license", 2.0)] * 2, "doc_id long, text string, score double")
    assert sorted((tuple(r)[1:6] for r in licenses.scan_licenses(df).collect()), key=str) == sorted([brute(t) for t in TEXTS] + [brute("mit license")] * 2, key=str)
    assert licenses.scan_licenses(df.limit(0)).count() == 0
