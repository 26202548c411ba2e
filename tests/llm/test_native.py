import hashlib

import duckdb
import pytest

from shardgraph.llm import line_dedup, mixing


def oracle(data, sql):
    con = duckdb.connect()
    con.execute(f"create view documents as select * from read_parquet('{data}/documents.parquet')")
    return sorted(con.sql(sql).fetchall(), key=str)


def test_line_dedup_equals_sql(spark, data):
    out = line_dedup.query(spark, data)
    assert sorted((tuple(r) for r in out.collect()), key=str) == oracle(data, line_dedup.ORACLE)


def test_mixing_equals_sql(spark, data):
    out = mixing.query(spark, data)
    assert sorted((tuple(r) for r in out.collect()), key=str) == oracle(data, mixing.ORACLE)


def brute_lines(docs, min_chars=40, min_docs=5):
    keys = {}
    for i, t in docs:
        for line in (t or "").split("\n"):
            k = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in line.strip(" \t\n\x0b\x0c\r"))
            if len(k) >= min_chars:
                keys.setdefault(k, set()).add(i)
    hot = {k: max((i for i in s if i is not None), default=None) for k, s in keys.items() if len(s) >= min_docs}
    out = []
    for i, t in docs:
        lines = (t or "").split("\n")
        kept = []
        for line in lines:
            k = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in line.strip(" \t\n\x0b\x0c\r"))
            if k not in hot or hot[k] == i:
                kept.append(line)
        out.append((i, len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return sorted(out, key=str)


def test_line_dedup_edges(spark):
    a, b = "x" * 40, "É" * 45
    docs = [(k, f"own {k}\n{a}\n\t{a.upper()} \n{b}\r\n") for k in range(6)] + [(None, a), (7, None), (8, ""), (9, f"{a}\n" * 3000), (9, f"{a}\n" * 3000), (10, b.lower()), (11, "\n\n")]
    df = spark.createDataFrame([(*d, "s", 0, 1) for d in docs], "doc_id long, text string, _drops string, _pos int, _d int")
    out = line_dedup.dedup_lines(df)
    assert out.columns[:5] == df.columns
    got = sorted(((r.doc_id, r._n_lines, r._n_dropped, hashlib.sha256(r.text.encode()).hexdigest()) for r in out.collect()), key=str)
    assert got == brute_lines(docs)
    assert line_dedup.dedup_lines(df.limit(0)).count() == 0


def test_targets_reach_no_limit_and_share_all(spark):
    rows = [(k, "w " * n, s) for k, (n, s) in enumerate([(10, "a"), (1000, "b"), (5, "c"), (500, "d"), (0, "e"), (40, None)] * 20)]
    out = mixing.mix(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    target = {r.source: r._target for r in out}
    size = {r.source: r._source_size for r in out}
    assert sum(target.values()) == pytest.approx(sum(size.values()))
    assert all(target[s] <= 3 * size[s] + 1e-9 for s in size)
    weight = {s: k % 3 + 1 for k, s in enumerate(["a", "b", "c", "d", "e", None])}
    free = {target[s] / weight[s] for s in size if target[s] < 3 * size[s] - 1e-6}
    assert max(free) == pytest.approx(min(free))
    for s in size:
        got = sum(r._copies * r._size for r in out if r.source == s)
        assert abs(got - target[s]) <= max((r._size for r in out if r.source == s), default=0)
    assert all(r._copies <= 3 for r in out)


def test_mixing_edges(spark):
    df = spark.createDataFrame([(1, None, None, 1), (None, "a b c", "x", 2), (2, "a", "x", 3), (2, "a", "x", 3), (3, "", "y", 4)], "doc_id long, text string, source string, _d int")
    out = mixing.mix(df).collect()
    assert len(out) == 5 and sorted(tuple(r) for r in mixing.mix(df).select("_copies", "_size").collect()) == sorted((r._copies, r._size) for r in out)
    assert mixing.mixed(df).columns == df.columns
    assert mixing.mix(df.limit(0)).count() == 0
