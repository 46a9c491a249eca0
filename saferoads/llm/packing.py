"""Packing by Karmarkar-Karp multiway differencing.

Every document is tokenized and closed with an end id. Spans of a whole window stand alone; what is left of a
document is cut into near-equal pieces of at most `piece` ids. Within a task, pieces are gathered until they fill
about `group` windows; largest differencing then merges partial partitions so that their imbalances oppose. If a
window of the result exceeds the capacity, the number of windows rises by one and the differencing runs again.
Only a group of pieces is held at a time and nothing is shuffled.

Null or empty texts have the end id alone. Equal rows are packed each on its own. An empty table gives no rows.
"""

from __future__ import annotations

import heapq
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from saferoads.llm.blocks import byte_texts, lean

WINDOW = 2048
END_ID = 1
SCHEMA = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint"


def difference(sizes: list[int], k: int) -> list[tuple[int, list[int]]]:
    """Karmarkar-Karp partition of sizes into k sets: (sum, indices) of the sets that are not empty.

    A partial partition is a list of sets in falling order of sums, without its empty sets. The two of largest
    spread are merged: the largest sums of one meet the smallest of the other.
    """
    if not sizes:
        return []
    if k == 1:
        return [(sum(sizes), list(range(len(sizes))))]
    heap = [(-s, i, [(s, [i])]) for i, s in enumerate(sizes)]
    heapq.heapify(heap)
    tick = len(sizes)
    while len(heap) > 1:
        _, _, left = heapq.heappop(heap)
        _, _, right = heapq.heappop(heap)
        over = len(left) + len(right) - k
        if over <= 0:
            merged = left + right
        else:
            # Sets number len(left)-over.. of the left meet the last `over` of the right, in opposite order.
            a, b = len(left) - over, len(right) - over
            met = [(x[0] + y[0], x[1] + y[1]) for x, y in zip(left[a:], reversed(right[b:]), strict=True)]
            merged = left[:a] + right[:b] + met
        merged.sort(key=lambda s: -s[0])
        spread = merged[0][0] - (merged[-1][0] if len(merged) == k else 0)
        heapq.heappush(heap, (-spread, tick, merged))
        tick += 1
    return heap[0][2]


def fill_windows(sizes: list[int], window: int) -> list[tuple[int, list[int]]]:
    """Near-equal windows; their number rises until none exceeds the capacity."""
    k = max(1, -(-sum(sizes) // window))
    while True:
        sets = difference(sizes, k)
        if max(s for s, _ in sets) <= window:
            return sets
        k += 1


def cut_points(n: int, window: int, piece: int) -> list[int]:
    """Starts of the pieces of a document of n ids, and n."""
    whole = n // window * window
    rest = n - whole
    parts = -(-rest // piece)
    return [*range(0, whole, window), *(whole + rest * i // parts for i in range(parts)), n]


def load_encoder(bpe_json: bytes, ranks: bytes, pattern: str):
    """Encoder to numpy ids. The rank table gives the ids of the tokenizers file; texts that name a special token,
    or hold characters on which Unicode versions may differ, go through the tokenizers library itself."""
    import base64
    import re

    import tiktoken
    from tokenizers import Tokenizer

    exact = Tokenizer.from_str(bpe_json.decode())
    table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, ranks.splitlines())}
    fast = tiktoken.Encoding("byte_bpe", pat_str=pattern, mergeable_ranks=table, special_tokens={})
    odd = re.compile("[^\x00-ɏ‐-‧€]|" + "|".join(re.escape(t.content) for t in exact.get_added_tokens_decoder().values()))

    def encode(text: str) -> np.ndarray:
        if odd.search(text):
            return np.array(exact.encode(text, add_special_tokens=False).ids, np.uint32)
        return fast.encode_to_numpy(text)

    return encode


def pack(docs: DataFrame, vocabulary: dict, window: int = WINDOW, piece: int = 512, group: int = 128, spare: int = 512, with_ids: bool = False) -> DataFrame:
    """docs: doc_id, text. vocabulary: bpe_json and ranks (file contents) and pattern. One row per piece."""

    @lean
    def run(batches):
        from pyspark import TaskContext

        encode = load_encoder(**vocabulary)
        first_id, made = TaskContext.get().partitionId() << 40, 0
        held: list[tuple] = []
        total = 0

        def rows_of(group_rows):
            nonlocal made
            sets = fill_windows([r[2] for r in group_rows], window)
            out = []
            for _, members in sets:
                at = 0
                for m in members:
                    out.append((*group_rows[m][:5], first_id + made, at, group_rows[m][5]))
                    at += group_rows[m][2]
                made += 1
            return out

        def batch_of(rows):
            cols = list(zip(*rows, strict=True))
            arrays = [pa.array(c, pa.int64()) for c in cols[:7]]
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
            if with_ids:
                arrays.append(pa.array([np.frombuffer(x, np.uint32).astype(np.int32) for x in cols[7]], pa.list_(pa.int32())))
                names.append("ids")
            return pa.RecordBatch.from_arrays(arrays, names)

        for batch in batches:
            ready: list[tuple] = []
            for doc, raw in zip(batch.column("doc_id").to_pylist(), byte_texts(batch.column("text")), strict=True):
                ids = np.append(encode(raw.decode("utf-8", "replace")), np.uint32(END_ID)).astype("<u4")
                n, points = len(ids), cut_points(len(ids), window, piece)
                for a, b in zip(points, points[1:], strict=False):
                    part = ids[a:b].tobytes()
                    row = (doc, a, b - a, zlib.crc32(part), n, part if with_ids else None)
                    if b - a == window:
                        ready.append((*row[:5], first_id + made, 0, row[5]))
                        made += 1
                        continue
                    held.append(row)
                    total += b - a
                    if total >= group * window - spare:
                        ready += rows_of(held)
                        held, total = [], 0
            if ready:
                yield batch_of(ready)
        if held:
            yield batch_of(rows_of(held))

    return docs.select("doc_id", "text").mapInArrow(run, SCHEMA + (", ids array<int>" if with_ids else ""))


def read_vocabulary(bpe_path: str, rank_path: str, pattern: str) -> dict:
    """File contents of a tokenizer of fixed size, to send with the task."""
    with open(bpe_path, "rb") as a, open(rank_path, "rb") as b:
        return {"bpe_json": a.read(), "ranks": b.read(), "pattern": pattern}
