import hashlib
import random
import re

import numpy as np
import pytest

from phraseloom.llm import byte_words as bw
from phraseloom.llm import decontamination as dc

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def tokens(text):
    return WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


def brute(docs, items, window):
    windows = {}
    for key, text in items:
        words = tokens(text)
        size = min(window, len(words))
        for i in range(len(words) - size + 1 if words else 0):
            windows.setdefault(tuple(words[i : i + size]), set()).add(key)
    out = []
    for text in docs:
        words, hit, found = tokens(text), set(), set()
        for size in {len(w) for w in windows}:
            for i in range(len(words) - size + 1):
                if (w := tuple(words[i : i + size])) in windows:
                    hit |= set(range(i, i + size))
                    found |= windows[w]
        names = sorted(str(k) for k in found if k is not None)
        out.append((len(words), len(hit), len(names), hashlib.sha256(",".join(names).encode()).hexdigest()))
    return out


ITEMS = [(1, "the quick brown fox jumps over the lazy dog near the quiet river"), (2, "Tiny item"), (10, "tiny ITEM"), (None, "x"), (3, None), (4, "  --  "), (1, "the quick brown fox jumps over the lazy dog near the quiet river")]


def test_edges(spark, edges, edge_rows, nothing):
    items = spark.createDataFrame(ITEMS, "item_id long, text string")
    docs = edges.unionByName(spark.createDataFrame([(*edge_rows[0][:1], "a TINY, item! x tiny\titem", *edge_rows[0][2:])], edges.schema))
    got = sorted((r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"]) for r in dc.report(docs, items).collect())
    assert got == sorted(brute([t[1] for t in edge_rows] + ["a TINY, item! x tiny\titem"], ITEMS, 10))
    kept = dc.decontaminate(docs, items)
    assert kept.columns == docs.columns and kept.count() == sum(h == 0 for _, h, *_ in got)
    assert dc.report(nothing, items).count() == 0 and dc.report(docs, items.limit(0)).where("contaminated").count() == 0


def test_blocks_of_the_benchmark_give_the_same(spark, edges):
    items = spark.createDataFrame(ITEMS, "item_id long, text string")
    whole, parts = (sorted(map(tuple, dc.report(edges, items, block_bytes=b).drop("longest_match", "longest_at").collect()), key=repr) for b in (1 << 20, 20))
    assert whole == parts


@pytest.mark.parametrize("seed", range(6))
def test_random_words_against_brute_force(seed, monkeypatch):
    import pyarrow as pa

    r = random.Random(seed)
    make = lambda n: " ".join(r.choice("abc") for _ in range(n))
    items = [(i, make(r.randint(0, 8))) for i in range(6)]
    docs = [make(r.randint(0, 40)) for _ in range(15)] + ["", None]
    values, at = bw.words(*bw.buffers(pa.array([t for _, t in items])), bw.ALNUM)
    test = dc.TestBlock(values, at, [str(k) for k, _ in items], 4)
    for words in (1 << 20, 16):
        monkeypatch.setattr(dc, "SHARD_WORDS", words)
        got = list(dc.scan_rows(pa.array(docs), [test]))
        want = brute(docs, items, 4)
        assert [(a, b, c) for a, b, c, *_ in got] == [w[:3] for w in want]
        best = max((n for i, d in items for j in range(len(tokens(d))) for n in range(1, len(tokens(d)) - j + 1) if any(tokens(d)[j : j + n] == tokens(x)[k : k + n] for x in docs for k in range(len(tokens(x))))), default=0)
        assert max(g[4] for g in got) == best


@pytest.mark.parametrize("seed", range(4))
def test_every_document_gets_its_own_longest_match(seed, monkeypatch):
    """Copies of one passage all report it, whatever the shards and blocks."""
    import pyarrow as pa

    r = random.Random(seed)
    make = lambda n: " ".join(r.choice("abcd") for _ in range(n))
    items = [make(r.randint(1, 12)) for _ in range(5)]
    docs = [make(3) + " x " + items[0] + " y " + make(4)] * 9 + [make(r.randint(0, 30)) for _ in range(9)] + ["z", "", None]
    want = []
    for text in docs:
        d, best, at = tokens(text), 0, -1
        for i in range(len(d)):
            n = max((n for w in map(tokens, items) for j in range(len(w)) for n in range(1, len(w) - j + 1) if d[i : i + n] == w[j : j + n]), default=0)
            best, at = (n, i) if n > best else (best, at)
        want.append((best, at))
    blocks = [dc.TestBlock(*bw.words(*bw.buffers(pa.array(part)), bw.ALNUM), [str(k) for k in range(len(part))], 4) for part in (items, items[:2], items[2:])]
    for words in (1 << 20, 16):
        monkeypatch.setattr(dc, "SHARD_WORDS", words)
        for use in (blocks[:1], blocks[1:]):
            assert [g[4:] for g in dc.scan_rows(pa.array(docs), use)] == want


def test_suffix_array_orders_suffixes():
    r = np.random.default_rng(1)
    values = r.integers(0, 3, 200).astype(np.uint64)
    end = np.repeat([50, 120, 200], [50, 70, 80])
    order = dc.suffix_array(values, end, 64)
    suffixes = [tuple(values[i : min(end[i], i + 64)].tolist()) for i in order]
    assert suffixes == sorted(suffixes) and sorted(order.tolist()) == list(range(200))
