"""Packing documents into training sequences by minimum bin slack.

A document longer than a sequence gives whole sequences and a rest.  Rests are
packed a block at a time: the longest one that is left opens a sequence, and
the multiset of other lengths that fills it best is found by a subset-sum
program whose reachable sums are the bits of one number.  The bits before each
length are kept, so walking back tells how many of each length were taken.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from pathalgebra.llm.memory import lean
from pathalgebra.llm.tokens import shared_encoder, tokenizer_path

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
_ARROW = pa.schema([(n, pa.int64()) for n in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")])


def best_fill(counts: dict[int, int], lengths: list[int], room: int) -> dict[int, int]:
    """How many of each length come closest to ``room`` without exceeding it.

    ``lengths``: those of ``counts`` in falling order.  Fewer and longer pieces
    are preferred, as the program stops once the room is filled exactly.
    """
    reach, mask, goal = 1, (1 << (room + 1)) - 1, 1 << room
    steps: list[tuple[int, int, int]] = []
    for length in lengths:
        if length > room:
            continue
        left = min(counts[length], room // length)
        take = 1
        while left:
            take = min(take, left)
            steps.append((length, take, reach))
            reach |= (reach << (length * take)) & mask
            left -= take
            take *= 2
        if reach & goal:
            break
    total = reach.bit_length() - 1
    taken: dict[int, int] = {}
    for length, take, before in reversed(steps):
        if not before >> total & 1:
            taken[length] = taken.get(length, 0) + take
            total -= length * take
    return taken


def minimum_bin_slack(sizes: list[int], capacity: int) -> list[list[int]]:
    """Bins of indices into ``sizes``, each of at most ``capacity``.

    Every size must be between 1 and the capacity.  Ties go to the first index.
    """
    pools: dict[int, list[int]] = {}
    for i in range(len(sizes) - 1, -1, -1):
        pools.setdefault(sizes[i], []).append(i)
    counts = {k: len(v) for k, v in pools.items()}
    lengths = sorted(pools, reverse=True)
    bins = []
    while lengths:
        longest = lengths[0]
        members = [longest]
        counts[longest] -= 1
        chosen = best_fill(counts, lengths, capacity - longest)
        for length, n in chosen.items():
            members += [length] * n
            counts[length] -= n
        bins.append([pools[length].pop() for length in members])
        if any(counts[x] == 0 for x in {longest, *chosen}):
            lengths = [x for x in lengths if counts[x]]
    return bins


def pack_documents(documents: DataFrame, tokenizer: str | None = None, capacity: int = 2048, end_id: int = 1, block: int = 50_000) -> DataFrame:
    """One row per piece, for all documents.

    Null text is empty: the end id alone.  Documents are cut at multiples of the
    capacity only.  A block of rests is what a task has read, ``block`` documents
    at most, so no shuffle is needed and one sequence per block may be short.
    Sequence ids are unique, not dense.  Repeated rows are packed like others; a
    null doc_id stays null.  Other columns are ignored; no rows give no rows.
    """
    tokenizer = tokenizer or tokenizer_path()

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = shared_encoder(tokenizer, end_id)
        next_id = TaskContext.get().partitionId() << 40
        rests: list[tuple] = []

        def flush() -> Iterator[pa.RecordBatch]:
            nonlocal next_id
            rows = []
            for members in minimum_bin_slack([r[2] for r in rests], capacity):
                offset = 0
                for i in members:
                    rows.append((*rests[i], next_id, offset))
                    offset += rests[i][2]
                next_id += 1
            rests.clear()
            yield as_batch(rows)

        for batch in batches:
            rows = []
            doc_ids = batch.column(0).to_pylist()
            for doc_id, ids in zip(doc_ids, encoder.encode(batch.column(1)), strict=True):
                n = len(ids)
                ids = np.ascontiguousarray(ids, "<u4")
                whole = n - n % capacity
                for at in range(0, whole, capacity):
                    rows.append((doc_id, at, capacity, zlib.crc32(ids[at : at + capacity]), n, next_id, 0))
                    next_id += 1
                if n > whole:
                    rests.append((doc_id, whole, n - whole, zlib.crc32(ids[whole:]), n))
                    if len(rests) >= block:
                        yield from flush()
            yield as_batch(rows)
        yield from flush()

    return documents.select("doc_id", "text").mapInArrow(lean(pack, alone=False), PIECES)


def as_batch(rows: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) if rows else [()] * len(_ARROW)
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], schema=_ARROW)
