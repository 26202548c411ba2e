import hashlib
import random

import pytest

from shardgraph.llm import fingerprints as fp


def test_span_hashes_agree_with_spans():
    rng = random.Random(1)
    text = "".join(rng.choice("abé") for _ in range(300)) * 2
    p = fp.Prefixes(fp.points(text))
    for _ in range(300):
        i, j, n = rng.randrange(600), rng.randrange(600), rng.randrange(40)
        assert fp.same_span(p, i, p, j, n) == (i + n <= 600 and j + n <= 600 and text[i : i + n] == text[j : j + n])
    for _ in range(100):
        i, j = rng.randrange(600), rng.randrange(600)
        want = next((k for k in range(600 - max(i, j)) if text[i + k] != text[j + k]), 600 - max(i, j))
        assert fp.common_extension(p, i, p, j) == want


def test_known_polynomial():
    b = fp.BASES[0]
    want = sum((ord(c) + 1) * pow(b, k, fp.PRIME) for k, c in enumerate("bcd")) % fp.PRIME
    assert fp.Prefixes(fp.points("abcde")).span(1, 4) >> 31 == want


def test_runs_do_not_matter(monkeypatch):
    text = "".join(random.Random(2).choice("abcdefg ") for _ in range(5000))
    whole = fp.fingerprint(text)
    s = fp.Sketch()
    for k in range(0, 5000, 7):
        s.add(fp.points(text[k : k + 7]))
    assert s.text() == whole
    monkeypatch.setattr(fp, "CHUNK", 64)
    assert fp.fingerprint(text) == whole
    assert fp.fingerprint("") == fp.fingerprint("") != fp.fingerprint("a")


def plain_fingerprint(text):
    """The fingerprint by whole numbers of any size, one window after another."""
    h = lambda c, base: sum((ord(x) + 1) * pow(base, k, fp.PRIME) for k, x in enumerate(c)) % fp.PRIME
    whole = h(text, fp.BASES[0]) << 31 | h(text, fp.BASES[1])
    least = [None] * 64
    windows = [h(text[k : k + 12], fp.BASES[0]) for k in range(len(text) - 11)] or ([whole] if text else [])
    for w in windows:
        x = w * 0x9E3779B97F4A7C15 % 2**64
        x = (x ^ x >> 29) * 0xBF58476D1CE4E5B9 % 2**64
        slot = x >> 58
        least[slot] = x if least[slot] is None else min(x, least[slot])
    return f"{len(text):08x}{whole:016x}" + "".join("0000" if x is None else f"{max(1, x >> 8 & 0xFFFF):04x}" for x in least)


def plain_likeness(a, b):
    if a == b:
        return 1.0
    x, y = ([f[k : k + 4] for k in range(24, len(f), 4)] for f in (a, b))
    some = [(p, q) for p, q in zip(x, y, strict=True) if (p, q) != ("0000", "0000")]
    j = sum(p == q for p, q in some) / len(some) if some else 0.0
    return 2 * j / (1 + j)


def brute(docs):
    rows = sorted(docs, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or ""))
    out = []
    for k, (i, t) in enumerate(rows):
        t, nxt = t or "", rows[(k + 1) % len(rows)][1] or ""
        cut = len(t) // 4
        e = t[: len(t) - cut] + nxt[:cut]
        f, g = plain_fingerprint(t), plain_fingerprint(e)
        out.append((i, len(t), hashlib.sha256(e.encode()).hexdigest(), f, g, plain_likeness(f, g), plain_likeness(f, plain_fingerprint(nxt))))
    return sorted(out, key=str)


def test_whole_table(spark, data):
    rows = fp.query(spark, data).collect()
    docs = sorted(((r.doc_id, r.text) for r in spark.read.parquet(f"{data}/documents.parquet").collect()), key=lambda r: r[0])
    assert len(rows) == len(docs)
    some = [k for k in range(len(docs) - 1) if len(docs[k][1] or "") < 3000][:60]  # long texts take too long by plain numbers
    got = {r.doc_id: tuple(r)[:7] for r in rows}
    for k in some:
        assert got[docs[k][0]] == next(r for r in brute(docs[k : k + 2]) if r[0] == docs[k][0])
    long = [r for r in rows if r.n_chars > 400]
    assert sum(r.near_edited for r in long) / len(long) == pytest.approx(0.75, abs=0.05)
    assert sum(r.near_edited > r.near_next for r in long) > 0.95 * len(long)


@pytest.mark.parametrize("docs", [[], [(None, "only")], [(None, "a b c d"), (None, None), (4, "w x y z" * 30), (4, "w x y z" * 30), (4, "other text"), (1, ""), (9, "é" * 50)], [(7, "single document here")], [(2, "x" * 40), (1, "y" * 8)]])
def test_edges(spark, docs):
    df = spark.createDataFrame([(*d, "s") for d in docs], "doc_id long, text string, n_chars string")
    assert sorted((tuple(r)[:7] for r in fp.fingerprints(df).collect()), key=str) == brute(docs)
