"""Encoding to and decoding from the pieces of a given model, by batched Viterbi in numpy.

The best segmentation has the largest sum of piece scores. White space marks the start of a word, and no piece of the
model crosses such a start, so every distinct word of a block is solved once. Words of equal length advance together:
the hash of each substring from the current byte is probed in the sorted keys of the pieces, and better sums replace
the best at the substring's end with a backpointer. A character that no piece covers becomes its bytes' pieces (or the
unknown piece). Ties go to the longer last piece.

Null texts count as empty and have no pieces. The marker of white space in a text counts as a space. An empty table gives no rows.
"""

from __future__ import annotations

import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from saferoads.llm.blocks import lean, mixed, powers_of, text_blocks, word_hashes

SPACE = "▁".encode()
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
LONG_WORD = 48
BASE = 0x9E3779B97F4A7C15


def fields(raw: bytes):
    """(number, value) of the fields of a protocol buffer message."""

    def varint(i):
        value = shift = 0
        while True:
            value |= (raw[i] & 127) << shift
            shift += 7
            i += 1
            if raw[i - 1] < 128:
                return value, i

    i = 0
    while i < len(raw):
        tag, i = varint(i)
        if tag & 7 == 0:
            value, i = varint(i)
        elif tag & 7 == 2:
            size, i = varint(i)
            value, i = raw[i : i + size], i + size
        else:
            size = 4 if tag & 7 == 5 else 8
            value, i = raw[i : i + size], i + size
        yield tag >> 3, value


class Pieces:
    """A model file: piece strings (spaces for the marker), scores, kinds; sorted hashes of the pieces to match."""

    def __init__(self, raw: bytes):
        self.text, self.score, self.kind = [], [], []
        self.prefix = True
        for number, value in fields(raw):
            if number == 1:
                piece = dict(fields(value))
                self.text.append(piece.get(1, b"").replace(SPACE, b" "))
                self.score.append(struct.unpack("<f", piece[2])[0] if 2 in piece else 0.0)
                self.kind.append(piece.get(3, NORMAL))
            elif number == 3:
                options = dict(fields(value))
                self.prefix = bool(options.get(3, 1))
                if options.get(2) or options.get(4, 1):
                    raise ValueError("only models without character maps and white space removal are supported")
        self.kind = np.array(self.kind)
        self.score = np.array(self.score, np.float32)
        used = np.flatnonzero((self.kind == NORMAL) | (self.kind == USER))
        used = np.array([i for i in used if self.text[i]])
        self.unknown = int(np.flatnonzero(self.kind == UNKNOWN)[0])
        self.unknown_score = np.float32(self.score[self.kind == NORMAL].min() - np.float32(10))
        self.byte_ids = np.full(256, -1)
        for i in np.flatnonzero(self.kind == BYTE):
            self.byte_ids[int(self.text[i][3:5], 16)] = i
        if any(b" " in self.text[i].lstrip(b" ") for i in used):
            raise ValueError("a piece crosses the start of a word")
        sizes = np.array([len(self.text[i]) for i in used])
        ends = np.cumsum(sizes)
        h = word_hashes(np.frombuffer(b"".join(self.text[i] for i in used), np.uint8), ends - sizes, ends)
        order = np.argsort(h)
        self.keys, self.ids, self.longest = h[order], used[order], int(sizes.max())
        # Every beginning of a piece, with the piece's id where it is one: a substring that is none ends a probe.
        first = np.repeat(ends - sizes, sizes)
        stop = np.arange(len(first)) + 1
        h = word_hashes(np.frombuffer(b"".join(self.text[i] for i in used), np.uint8), first, stop)
        self.begin = np.unique(h)
        self.begin_id = np.full(len(self.begin), -1)
        self.begin_id[np.searchsorted(self.begin, self.keys)] = self.ids
        # What decoding writes for each id.
        written = [bytes([int(t[3:5], 16)]) if k == BYTE else b"" if k == CONTROL else " ⁇ ".encode() if k == UNKNOWN else t for t, k in zip(self.text, self.kind, strict=True)]
        sizes = np.array([len(w) for w in written])
        self.out_start, self.out_size = np.cumsum(sizes) - sizes, sizes
        self.out = np.frombuffer(b"".join(written), np.uint8)

    def match(self, h: np.ndarray) -> np.ndarray:
        """Id of the piece of each hash, -1 where there is none."""
        at = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
        return np.where(self.keys[at] == h, self.ids[at], -1)


CHAR_SIZE = np.ones(256, np.int64)
CHAR_SIZE[0xC0:0xE0], CHAR_SIZE[0xE0:0xF0], CHAR_SIZE[0xF0:] = 2, 3, 4


def solve_equal(rows: np.ndarray, pieces: Pieces) -> tuple[np.ndarray, np.ndarray]:
    """Piece ids of words of one length, one word after the other, and their numbers; rows: words x bytes."""
    count, n = rows.shape
    best = np.full((n + 1, count), -np.inf, np.float32)
    best[0] = 0
    came, used = np.zeros((n + 1, count), np.int32), np.full((n + 1, count), -1, np.int32)
    terms = np.ascontiguousarray(rows.T).astype(np.uint64) + np.uint64(1)
    weights = powers_of(pow(BASE, -1, 1 << 64), n)
    for s in range(n):
        live = np.flatnonzero(best[s] > -np.inf)
        if not len(live):
            continue
        size = np.minimum(CHAR_SIZE[rows[live, s]], n - s)
        bare, here = np.ones(count, bool), best[s]
        at, h = live, np.zeros(len(live), np.uint64)
        for m in range(1, min(pieces.longest, n - s) + 1):
            h = h + terms[s + m - 1, at] * weights[m - 1]
            full = mixed(h + np.uint64(m))
            place = np.minimum(np.searchsorted(pieces.begin, full), len(pieces.begin) - 1)
            on = pieces.begin[place] == full
            if not on.all():
                at, h, place = at[on], h[on], place[on]
            if not len(at):
                break
            piece = pieces.begin_id[place]
            hit = piece >= 0
            to, found = at[hit], piece[hit]
            bare[to[CHAR_SIZE[rows[to, s]] == m]] = False
            sums = here[to] + pieces.score[found]
            better = sums > best[s + m, to]
            to, found = to[better], found[better]
            best[s + m, to], came[s + m, to], used[s + m, to] = sums[better], s, found
        open_ = bare[live]
        to, end = live[open_], s + size[open_]
        sums = here[to] + pieces.unknown_score
        better = sums > best[end, to]
        to, end = to[better], end[better]
        best[end, to], came[end, to], used[end, to] = sums[better], s, pieces.unknown
    return backtrace(rows, came, used, pieces)


def solve_long(word: np.ndarray, pieces: Pieces) -> tuple[np.ndarray, np.ndarray]:
    """One long word: all substrings are probed for each size at once, then sums run along the word."""
    n = len(word)
    starts: list[list[tuple[int, int]]] = [[] for _ in range(n)]
    for m in range(1, min(pieces.longest, n) + 1):
        at = np.arange(n - m + 1)
        found = pieces.match(word_hashes(word, at, at + m))
        for s in np.flatnonzero(found >= 0).tolist():
            starts[s].append((m, int(found[s])))
    best, came, used = np.full(n + 1, -np.inf, np.float32), np.zeros((n + 1, 1), np.int32), np.full((n + 1, 1), -1, np.int32)
    best[0] = 0
    size = CHAR_SIZE[word].tolist()
    for s in range(n):
        if best[s] == -np.inf:
            continue
        edges = [(m, i, pieces.score[i]) for m, i in starts[s]]
        if not any(m == size[s] for m, _, _ in edges):
            edges.append((min(size[s], n - s), pieces.unknown, pieces.unknown_score))
        for m, i, score in edges:
            if best[s] + score > best[s + m]:
                best[s + m], came[s + m, 0], used[s + m, 0] = best[s] + score, s, i
    return backtrace(word[None, :], came, used, pieces)


def backtrace(rows: np.ndarray, came: np.ndarray, used: np.ndarray, pieces: Pieces) -> tuple[np.ndarray, np.ndarray]:
    """Follows the backpointers of all rows together; unknown pieces become bytes where the model has them."""
    count, n = rows.shape
    at, live = np.full(count, n), np.arange(count)
    who, what, where, stop = [], [], [], []
    while len(live):
        end = at[live]
        before = came[end, live]
        who.append(live)
        what.append(used[end, live])
        where.append(before)
        stop.append(end)
        at[live] = before
        live = live[before > 0]
    who, what, where, stop = (np.concatenate(x) for x in (who, what, where, stop))
    order = np.lexsort((where, who))
    who, what, where, stop = who[order], what[order], where[order], stop[order]
    if (pieces.byte_ids >= 0).all() and (what == pieces.unknown).any():
        repeat = np.where(what == pieces.unknown, stop - where, 1)
        first = np.repeat(np.cumsum(repeat) - repeat, repeat)
        byte = rows[np.repeat(who, repeat), np.minimum(np.repeat(where, repeat) + np.arange(len(first)) - first, n - 1)]
        what = np.where(np.repeat(what, repeat) == pieces.unknown, pieces.byte_ids[byte], np.repeat(what, repeat))
        who = np.repeat(who, repeat)
    return what.astype(np.int32), np.bincount(who, minlength=count)


class Encoder:
    """Encodes blocks of texts; solved words are kept, at most `keep` of them."""

    def __init__(self, pieces: Pieces, keep: int = 1_000_000):
        self.pieces, self.keep = pieces, keep
        self._reset()

    def _reset(self):
        self.known, self.start, self.size = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.flat = np.zeros(0, np.int32)

    def encode(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and the bounds of each text's."""
        prefix = b" " if self.pieces.prefix else b""
        shown = [prefix + t.replace(SPACE, b" ") if t else b"" for t in texts]
        sizes = np.fromiter(map(len, shown), np.int64, len(shown))
        ends = np.cumsum(sizes)
        data = np.frombuffer(b"".join(shown), np.uint8)
        if not len(data):
            return np.zeros(0, np.int32), np.zeros(len(texts) + 1, np.int64)
        begin = data == 32
        begin[1:] &= data[:-1] != 32
        begin[(ends - sizes)[sizes > 0]] = True
        ws = np.flatnonzero(begin)
        we = np.append(ws[1:], len(data))
        h = word_hashes(data, ws, we)
        distinct, first, inverse = np.unique(h, return_index=True, return_inverse=True)
        at = np.minimum(np.searchsorted(self.known, distinct), max(len(self.known) - 1, 0))
        new = np.flatnonzero(self.known[at] != distinct) if len(self.known) else np.arange(len(distinct))
        if len(new):
            if len(self.known) + len(new) > self.keep:
                self._reset()
                new = np.arange(len(distinct))
            self._learn(data, distinct[new], ws[first[new]], we[first[new]])
            at = np.searchsorted(self.known, distinct)
        word = at[inverse]
        size = self.size[word]
        stop = np.cumsum(size)
        ids = self.flat[np.repeat(self.start[word] - (stop - size), size) + np.arange(size.sum())]
        of = np.searchsorted(ends, ws, "right")
        per_text = np.bincount(of, size, len(texts)).astype(np.int64)
        return ids, np.concatenate([[0], np.cumsum(per_text)])

    def _learn(self, data, hashes, ws, we):
        size = we - ws
        flat, start, count, at = [self.flat], np.zeros(len(hashes), np.int64), np.zeros(len(hashes), np.int64), len(self.flat)
        for n in np.unique(size):
            group = np.flatnonzero(size == n)
            for part in np.array_split(group, -(-len(group) // 20_000)) if n <= LONG_WORD else group[:, None]:
                ids, counts = solve_equal(data[ws[part][:, None] + np.arange(n)], self.pieces) if n <= LONG_WORD else solve_long(data[ws[part[0]] : we[part[0]]], self.pieces)
                flat.append(ids)
                count[part], start[part] = counts, at + np.cumsum(counts) - counts
                at += len(ids)
        self.flat = np.concatenate(flat)
        known = np.concatenate([self.known, hashes])
        order = np.argsort(known)
        self.known, self.start, self.size = known[order], np.concatenate([self.start, start])[order], np.concatenate([self.size, count])[order]


def decode(ids: np.ndarray, bounds: np.ndarray, pieces: Pieces) -> list[bytes]:
    """Texts of all id sequences."""
    size = pieces.out_size[ids]
    stop = np.cumsum(size)
    raw = pieces.out[np.repeat(pieces.out_start[ids] - (stop - size), size) + np.arange(size.sum())].tobytes()
    at = np.concatenate([[0], stop])[bounds].tolist()
    cut = 1 if pieces.prefix else 0
    return [raw[a + cut * (raw[a : a + 1] == b" ") : b] if b > a else b"" for a, b in zip(at, at[1:], strict=False)]


def encode_documents(docs: DataFrame, model: bytes) -> DataFrame:
    """doc_id, n_tokens, ids, round_trip (decoding gives the text) for every row."""

    @lean
    def run(batches):
        encoder = Encoder(Pieces(model))
        for batch in batches:
            keys = batch.column("doc_id").cast(pa.int64())
            for a, b, texts in text_blocks(batch.column("text"), 2 << 20):
                ids, bounds = encoder.encode(texts)
                back = [x == t.replace(SPACE, b" ") for x, t in zip(decode(ids, bounds, encoder.pieces), texts, strict=True)]
                lists = pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(ids.astype(np.int32)))
                yield pa.RecordBatch.from_arrays([keys.slice(a, b - a), pa.array(np.diff(bounds)), lists, pa.array(back)], ["doc_id", "n_tokens", "ids", "round_trip"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, n_tokens bigint, ids array<int>, round_trip boolean")


def decode_documents(encoded: DataFrame, model: bytes) -> DataFrame:
    """doc_id, text from doc_id, ids."""

    @lean
    def run(batches):
        pieces = Pieces(model)
        for batch in batches:
            lists = batch.column("ids").fill_null([]) if batch.column("ids").null_count else batch.column("ids")
            ids, sizes = lists.flatten().to_numpy(zero_copy_only=False), np.array([len(x) for x in lists], np.int64)
            texts = decode(ids, np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64), pieces)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), pa.array([t.decode("utf-8", "replace") for t in texts], pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id bigint, text string")
