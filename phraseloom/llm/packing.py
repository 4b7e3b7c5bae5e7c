"""Cost-balanced packing into fixed-length training sequences.

A document costs ``linear * tokens + quadratic * tokens^2`` (projections plus attention inside the document). Each
task tokenizes its rows and packs them in chunks of a bounded number of tokens, so nothing is shuffled and memory does
not grow with the input. In a chunk, whole multiples of the capacity become sequences of their own; the remainders, in
descending order, each go to the open sequence of lowest cost that still has room, and a remainder that fits nowhere is
cut to fill the roomiest sequences. Every sequence of a chunk but the last is full, so padding stays below one sequence
per chunk.

Defined cases: a null text packs like an empty one (its end mark only); texts of any length are cut; ties go to the
lower sequence and the earlier row; repeated rows are packed each on its own; an empty table gives no pieces.
"""

from __future__ import annotations

import base64
import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from phraseloom.llm.common import tidy

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, sequence_length long"
CAPACITY, END_ID = 2048, 1
CHUNK_TOKENS = 4 << 20
LINEAR, QUADRATIC = 1.0, 1.0 / 2048


def encoder(vocabulary: str = "byte_bpe_50k.tiktoken"):
    """The byte-level BPE of the named vocabulary file, as a function from a text to ids (same ids as its JSON form)."""
    import public_tokenizers
    import tiktoken

    with open(public_tokenizers.path(vocabulary), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    coding = tiktoken.Encoding("packing", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    return coding.encode_ordinary


def assign(lengths: np.ndarray, capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int]]:
    """Pieces ``(document, start, length, sequence, offset)`` of one chunk of documents."""
    pieces: list[tuple[int, int, int, int, int]] = []
    lengths = np.asarray(lengths, dtype=np.int64)
    sequence = 0
    for doc in np.flatnonzero(lengths >= capacity):
        for start in range(0, int(lengths[doc]) - capacity + 1, capacity):
            pieces.append((int(doc), start, capacity, sequence, 0))
            sequence += 1
    rest = lengths % capacity
    total = int(rest.sum())
    if not total:
        return pieces
    count = -(-total // capacity)
    room = np.full(count, capacity, np.int64)
    room[-1] = total - (count - 1) * capacity
    start_room = room.copy()
    # Sequences by cost; those without room for the document at hand wait and come back for a shorter one.
    open_by_cost = [(0.0, s) for s in range(count)]
    parked: list[tuple[int, float, int]] = []
    by_room = [(-int(r), s) for s, r in enumerate(room)]
    heapq.heapify(by_room)
    cost = np.zeros(count)

    def put(doc: int, start: int, length: int, s: int) -> None:
        pieces.append((doc, start, length, sequence + s, int(start_room[s] - room[s])))
        room[s] -= length
        cost[s] += LINEAR * length + QUADRATIC * length * length
        heapq.heappush(by_room, (-int(room[s]), s))

    for doc in np.lexsort((np.arange(len(rest)), -rest)):
        length, start = int(rest[doc]), int(lengths[doc] - rest[doc])
        if not length:
            break
        while parked and -parked[0][0] >= length:
            _, c, s = heapq.heappop(parked)
            heapq.heappush(open_by_cost, (c, s))
        while open_by_cost:
            c, s = open_by_cost[0]
            if c != cost[s] or not room[s]:  # an entry of the past
                heapq.heappop(open_by_cost)
            elif room[s] < length:
                heapq.heappop(open_by_cost)
                heapq.heappush(parked, (-int(room[s]), c, s))
            else:
                break
        if open_by_cost:
            s = heapq.heappop(open_by_cost)[1]
            put(int(doc), start, length, s)
            heapq.heappush(open_by_cost, (cost[s], s))
            continue
        while length:  # fits nowhere whole: fill the roomiest sequences
            free, s = heapq.heappop(by_room)
            if -free != room[s]:
                continue
            take = min(length, int(room[s]))
            put(int(doc), start, take, s)
            heapq.heappush(open_by_cost, (cost[s], s))
            start, length = start + take, length - take
    return pieces


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, vocabulary: str = "byte_bpe_50k.tiktoken", end_id: int = END_ID, chunk_tokens: int = CHUNK_TOKENS, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per piece; ``sequence_id`` holds the task's partition, then a count inside it."""
    kinds = pa.schema([("doc_id", pa.int64()), *[(n, pa.int64()) for n in ("start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "sequence_length")]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(vocabulary)
        base = TaskContext.get().partitionId() << 36
        keys: list = []
        ids: list[np.ndarray] = []
        held = 0

        def flush() -> pa.RecordBatch:
            nonlocal base, held
            pieces = sorted(assign(np.array([len(x) for x in ids], np.int64), capacity), key=lambda p: (p[3], p[4]))
            sizes: dict[int, int] = {}
            for p in pieces:
                sizes[p[3]] = sizes.get(p[3], 0) + p[2]
            columns = [
                [keys[p[0]] for p in pieces], [p[1] for p in pieces], [p[2] for p in pieces], [zlib.crc32(ids[p[0]][p[1] : p[1] + p[2]].tobytes()) for p in pieces],
                [len(ids[p[0]]) for p in pieces], [base + p[3] for p in pieces], [p[4] for p in pieces], [sizes[p[3]] for p in pieces],
            ]
            base += len(sizes)
            keys.clear()
            ids.clear()
            held = 0
            return pa.record_batch([pa.array(c, type=f.type) for c, f in zip(columns, kinds, strict=True)], schema=kinds)

        for batch in tidy(batches):
            for k, t in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                got = np.array([*encode(t.as_py() or ""), end_id], dtype="<u4")
                keys.append(k)
                ids.append(got)
                held += len(got)
                if held >= chunk_tokens:
                    yield flush()
        if keys:
            yield flush()

    return docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, SCHEMA)
