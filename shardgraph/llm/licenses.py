"""License scans: an Aho-Corasick automaton over words, and a shunting-yard parser for licence expressions."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

#: The base phrases and their labels.
BASE = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}
#: Further notice phrases, in words as the scan sees them, and the labels the method adds for them.
NOTICES = {
    "gnu lesser general public license": "lgpl", "gnu affero general public license": "agpl", "gnu free documentation license": "gfdl",
    "mozilla public license": "mpl", "eclipse public license": "epl", "european union public licence": "eupl", "boost software license": "bsl",
    "bsd license": "bsd", "2 clause bsd": "bsd-2-clause", "3 clause bsd": "bsd-3-clause", "redistribution and use in source and binary forms": "bsd",
    "isc license": "isc", "zlib license": "zlib", "the unlicense": "unlicense", "artistic license": "artistic", "open database license": "odbl",
    "permission is hereby granted free of charge": "mit", "apache license version 2 0": "apache-2.0", "general public license version 2": "gpl-2",
    "general public license version 3": "gpl-3", "cc by sa": "cc-by-sa", "cc by nc": "cc-by-nc", "cc by nd": "cc-by-nd", "cc by nc sa": "cc-by-nc-sa",
    "cc by nc nd": "cc-by-nc-nd", "cc0": "cc0", "creative commons attribution": "cc-by", "public domain": "public-domain", "all rights reserved": "all-rights-reserved",
}
TAG = "spdx license identifier"
#: How freely text under a licence may be used, by the start of its identifier; the longest start counts.
FREEDOM = {"": 0.4, "mit": 1.0, "apache": 1.0, "bsd": 1.0, "isc": 1.0, "zlib": 1.0, "unlicense": 1.0, "cc0": 1.0, "cc-by": 0.9, "cc-by-sa": 0.6, "cc-by-nc": 0.2, "cc-by-nd": 0.2, "mpl": 0.7, "epl": 0.7, "lgpl": 0.6, "gpl": 0.4, "agpl": 0.3}
_TAG_TEXT = re.compile(r"spdx[-_ ]license[-_ ]identifier\s*:[^\S\n]*([^\n]*)", re.ASCII | re.IGNORECASE)
_TOKEN = re.compile(r"\(|\)|[A-Za-z0-9][A-Za-z0-9.+-]*")
#: Binding strength of the operators.
STRENGTH = {"or": 1, "and": 2, "with": 3}
#: Every byte that a word can't hold becomes a space, and A-Z lower case.
_WORDS = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def parse(text: str) -> tuple[list[str], float] | None:
    """(licences, freedom) of the expression that text starts with, or None where it starts with none.

    or takes the freer side, and the stricter; with an exception a licence is half-way to free. The
    two stacks of the shunting-yard method hold operators and values; the longest valid start counts,
    so prose or a comment's end behind an expression does no harm.
    """
    ops: list[str] = []
    values: list[tuple[list[str], float]] = []
    best, operand = None, True

    def reduce(ops: list[str], values: list) -> None:
        (b, y), (a, x) = values.pop(), values.pop()
        op = ops.pop()
        values.append((a, (1 + x) / 2) if op == "with" else (a + b, max(x, y) if op == "or" else min(x, y)))

    for m in _TOKEN.finditer(text):
        t = m[0].lower()
        if operand:
            if t == "(":
                ops.append(t)
                continue
            if t == ")" or t in STRENGTH:
                break
            start = max((s for s in FREEDOM if t.startswith(s)), key=len)
            values.append(([t.rstrip("+").removesuffix("-or-later").removesuffix("-only")], FREEDOM[start]))
            operand = False
        elif t == ")":
            while ops and ops[-1] != "(":
                reduce(ops, values)
            if not ops:
                break
            ops.pop()
        elif t in STRENGTH:
            while ops and ops[-1] != "(" and STRENGTH[ops[-1]] >= STRENGTH[t]:
                reduce(ops, values)
            ops.append(t)
            operand = True
            continue
        else:
            break
        if "(" not in ops:
            o, v = ops[:], values[:]
            while o:
                reduce(o, v)
            best = v[0]
    return best


def automaton(phrases: dict[str, str]):
    """The automaton over phrases as space-framed words in UTF-8 bytes, one character for each byte."""
    import ahocorasick

    a = ahocorasick.Automaton()
    for phrase, label in phrases.items():
        framed = f" {phrase} ".encode().decode("latin-1")
        a.add_word(framed, (len(framed), label, phrase in BASE))
    a.make_automaton()
    return a


def scan(text: str, machine) -> tuple:
    """(n_words, n_base, first_word, last_word, base_labels, labels, score, freedom) of one text."""
    words = text.encode().translate(_WORDS).split()
    framed = b" " + b" ".join(words) + b" "
    base, places, labels, tagged = set(), [], set(), False
    gaps = None
    for end, (length, label, is_base) in machine.iter(framed.decode("latin-1")):
        if label is None:
            tagged = True
            continue
        labels.add(label)
        if is_base:
            gaps = np.flatnonzero(np.frombuffer(framed, "u1") == 32) if gaps is None else gaps
            base.add(label)
            places.append(int(np.searchsorted(gaps, end - length + 1)))
    sure, freedom = 0.7 if base else 0.5 if labels else 0.0, None
    if tagged:
        for m in _TAG_TEXT.finditer(text):
            if found := parse(m[1]):
                labels.update(found[0])
                freedom = found[1] if freedom is None else min(freedom, found[1])
                sure = 1.0
        sure = max(sure, 0.3)
    return len(words), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(base)), ",".join(sorted(labels)), sure, freedom


_SCHEMA = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_base", pa.int64()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("base_labels", pa.string()), ("labels", pa.string()), ("score", pa.float64()), ("freedom", pa.float64())])


def scan_licenses(docs: DataFrame, phrases: dict[str, str] | None = None) -> DataFrame:
    """One row a document: words, places of base phrases, labels, evidence score and the freedom its identifier tags give.

    score: 0 no trace, 0.3 a tag without a valid expression, 0.5 a notice, 0.7 a base phrase, 1 a
    tag with a valid expression. freedom: the strictest tagged expression's value, else null. A null
    or empty text has no words. Rows map one to one, so repeated rows, null ids and an empty table
    need nothing more; columns but doc_id and text are not read. Long texts take memory in proportion.
    """
    table = {TAG: None} | NOTICES | (phrases or {}) | BASE

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = automaton(table)
        for b in batches:
            rows = [scan(t or "", machine) for t in b.column("text").to_pylist()]
            cols = [list(c) for c in zip(*rows, strict=True)] if rows else [[] for _ in range(8)]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, f.type) for c, f in zip(cols, list(_SCHEMA)[1:], strict=True))], schema=_SCHEMA)

    return docs.select(docs["doc_id"].cast("bigint").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, freedom double")


def query(spark, sf_dir: str) -> DataFrame:
    return scan_licenses(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
