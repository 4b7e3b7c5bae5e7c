import zlib
from collections import defaultdict

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from phraseloom.llm import packing


@given(st.lists(st.integers(1, 700), max_size=60), st.sampled_from([64, 256]))
@settings(max_examples=200, deadline=None)
def test_assignment_is_a_partition_without_padding(lengths, capacity):
    pieces = packing.assign(np.array(lengths, np.int64), capacity)
    covered, filled = defaultdict(list), defaultdict(list)
    for doc, start, length, sequence, offset in pieces:
        assert length > 0
        covered[doc] += range(start, start + length)
        filled[sequence].append((offset, length))
    assert {d: sorted(c) for d, c in covered.items()} == {d: list(range(n)) for d, n in enumerate(lengths)}
    sizes = []
    for parts in filled.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= capacity
        sizes.append(at)
    assert sum(s < capacity for s in sizes) <= 1


def test_longest_documents_go_to_the_cheapest_sequences():
    pieces = packing.assign(np.array([40, 40, 20, 20, 10, 10, 60]), 100)
    cost = defaultdict(float)
    for _, _, length, sequence, _ in pieces:
        cost[sequence] += packing.LINEAR * length + packing.QUADRATIC * length**2
    assert len(cost) == 2 and len(pieces) == 7  # nothing is cut, both sequences are full


def test_pieces_hold_the_ids(edges, edge_rows, nothing):
    tokenizer = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    rows = packing.pack_documents(edges).collect()
    expected = defaultdict(int)
    for key, text, *_ in edge_rows:
        expected[key, len(tokenizer.encode(text or "", add_special_tokens=False).ids) + 1] += 1
    seen = defaultdict(list)
    for r in rows:
        seen[r["doc_id"], r["doc_tokens"]].append(r)
    assert set(seen) == set(expected)
    by_key = {(k, len(ids)): ids for k, t, *_ in edge_rows for ids in [[*tokenizer.encode(t or "", add_special_tokens=False).ids, 1]]}
    for (key, tokens), parts in seen.items():
        assert sum(p["length"] for p in parts) == tokens * expected[key, tokens]
        if expected[key, tokens] == 1 and key not in (4, None):
            ids = np.array(by_key[key, tokens], "<u4")
            for p in parts:
                assert p["ids_crc32"] == zlib.crc32(ids[p["start"] : p["start"] + p["length"]].tobytes())
    sequences = defaultdict(int)
    for r in rows:
        sequences[r["sequence_id"]] += r["length"]
    assert all(n <= 2048 for n in sequences.values()) and all(r["sequence_length"] == sequences[r["sequence_id"]] for r in rows)
    assert packing.pack_documents(nothing).count() == 0


def test_small_chunks(edges):
    pieces = packing.pack_documents(edges.coalesce(1), capacity=64, chunk_tokens=500)
    assert pieces.groupBy("sequence_id").sum("length").agg({"sum(length)": "max"}).first()[0] <= 64


@pytest.mark.parametrize("text", ["<|endoftext|> a", "tab\tand  spaces \n\n x", "日本語 straße 🙂", "don't we'll 12345 !!??"])
def test_same_ids_as_the_json_form(text):
    tokenizer = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    tokenizer.encode_special_tokens = True
    assert packing.encoder()(text) == tokenizer.encode(text, add_special_tokens=False).ids
