import random
import zlib

import numpy as np
from tokenizers import Tokenizer

from shardgraph.llm import packing
from shardgraph.llm.tokens import WordIds, default_vocabulary

DOCS = "doc_id long, text string, source string, length int"


def reference_ids(tokenizer, text):
    return [*tokenizer.encode(text or "", add_special_tokens=False).ids, 2]


def check(docs, rows, window):
    """Every id lies in one piece, checksums agree, sequences are gapless and padded only at their end."""
    tok = Tokenizer.from_file(default_vocabulary())
    want = [(d, len(i), tuple(i)) for d, t in docs for i in [reference_ids(tok, t)]]
    by_doc, seqs = {}, {}
    for r in rows:
        by_doc.setdefault((r.doc_id, r.doc_tokens), []).append(r)
        seqs.setdefault(r.sequence_id, []).append(r)
    ids = {}
    for d, n, i in want:
        ids.setdefault((d, n), []).append(np.array(i, "<u4"))
    assert set(ids) == set(by_doc)
    for key, arrays in ids.items():
        assert sum(r.length for r in by_doc[key]) == key[1] * len(arrays)
        for r in by_doc[key]:
            assert any(zlib.crc32(a[r.start : r.start + r.length].tobytes()) == r.ids_crc32 for a in arrays)
    padding = 0
    for parts in seqs.values():
        at = 0
        for r in sorted(parts, key=lambda r: r.offset):
            assert r.offset == at and r.length > 0
            at += r.length
        assert at <= window
        padding += 0 if at & (at - 1) == 0 else window - at
    return padding


def test_word_memory_equals_tokenizer():
    words, tok = WordIds(default_vocabulary()), Tokenizer.from_file(default_vocabulary())
    for t in ["", " ", "It's A test, ok.  x\n\ny\tz", "É. éx, ½. ΑΣ. straße,", "<|ENDOFTEXT|> <|endoftext|>. a.b.c,,", "a\x1fb  c \x85d", "İstanbul. DON'T. 12.5, 7."]:
        assert np.frombuffer(words.packed(t), "<u4").tolist() == tok.encode(t, add_special_tokens=False).ids


def test_fill_is_optimal():
    rng = random.Random(3)
    for _ in range(200):
        counts = {rng.randint(1, 40): rng.randint(1, 3) for _ in range(rng.randint(1, 5))}
        room = rng.randint(0, 60)
        used = packing.fill(counts, room)
        assert all(0 < n <= counts[k] for k, n in used.items())
        sums = {0}
        for k, n in counts.items():
            sums = {s + j * k for s in sums for j in range(n + 1) if s + j * k <= room}
        assert sum(k * n for k, n in used.items()) == max(sums)


def test_plan_takes_every_piece_once():
    rng = random.Random(5)
    for _ in range(30):
        counts = {rng.randint(1, 64): rng.randint(1, 50) for _ in range(20)}
        patterns, rest = packing.plan(counts, 64)
        total = dict(rest)
        for used, times in patterns:
            assert sum(k * n for k, n in used.items()) == 64
            for k, n in used.items():
                total[k] = total.get(k, 0) + n * times
        assert total == counts


def test_pack_whole_table(spark, data):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    rows = packing.query(spark, data).collect()
    assert check([(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()], rows, 4096) == 0


def test_pack_edge_rows(spark):
    rows = [(1, "a b c", "x", 1), (1, "a b c", "x", 1), (1, "other", "x", 1), (2, None, None, None), (None, "no id", "x", 1), (3, "", "x", 1), (4, "word " * 3000, "x", 1), (5, "lorem ipsum " * 90, "x", 1)]
    out = packing.pack(spark.createDataFrame(rows, DOCS), window=64).collect()
    assert check([(r[0], r[1]) for r in rows], out, 64) == 0
    assert packing.pack(spark.createDataFrame([], DOCS)).count() == 0


def test_words_with_trailing_marks_need_no_whole_encoding(monkeypatch):
    words, tok = WordIds(default_vocabulary()), Tokenizer.from_file(default_vocabulary())
    some = [h + m for h in ("abc", "Éa", "x", "ß", "don") for m in ("$$$", "...", "!?", ".%%%", "`", ")(", "\\", "'s", "'", '"\'s')]
    assert [words.look_up(w) for w in some] == [np.array(tok.encode(w, add_special_tokens=False).ids, "<u4").tobytes() for w in some]
    for m in ("$$$", ",***"):
        words[m]
    words.tokenizer = None
    assert words.look_up("heat$$$") + words.look_up("Rain,***")
