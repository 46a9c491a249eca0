"""Repeated windows by a depth-limited most-significant-digit radix order of all suffixes.

A text is a sequence of tokens: its bytes, or its words. Only the first `depth` tokens of a suffix matter: suffixes that
agree on them are exactly the starts of a repeated window. Each pass refines the groups of the pass before by a longer
digit and drops suffixes that are alone:

1. The first digit of a suffix is the least hash among the `gram`-token substrings of its window. Equal windows have
   equal digits, and neighbouring suffixes mostly share theirs, so one row stands for a run of suffixes.
2. The second digit is the whole span of the run. Spans that occur twice are repeated throughout.
3. Runs that share the first digit but not the span are cut into blocks of `step` suffixes, aligned at the gram that
   gave the digit. The tokens common to a block's windows are the third digit: a block alone in it has no repeated
   window. The tokens that a block's windows cover together are the fourth: blocks equal in it are repeated throughout.
4. The remaining blocks are ordered suffix by suffix, by their full depth.

Counts are pre-aggregated and rows of equal digits are joined to their counts, so a passage that a third of the
documents share is split like any skewed join; every pass carries one row for each distinct digit, not for each copy.
Text is moved for the documents that need blocks and for those that lose something; a bitmap of fixed size
keeps the others out of both shuffles. Intermediate tables are deleted as soon as no later pass reads them.

Null or empty texts have no window and lose nothing. A text occurring in several rows repeats itself, also under
one doc_id. Matches never cross documents. An empty table gives no rows. Ties do not arise: all copies are treated alike.
Other columns of docs may have any name.
"""

from __future__ import annotations

import hashlib
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from saferoads.llm.bitmap import bitmap_of, keep_marked, marked
from saferoads.llm.blocks import joined, lean, mixed, powers_of, space_table, text_blocks, unused_name, word_bounds, word_hashes
from saferoads.plans.runtime import drop, durable

DEPTH, GRAM, STEP = 400, 128, 16
#: Words of a passage, of the grams of its first digit, suffixes of a block.
PASSAGE, PASSAGE_GRAM, PASSAGE_STEP = 50, 12, 4
SEGMENT = 1 << 18
BASE = 0x9E3779B97F4A7C15
U = np.uint64
SPACE = re.compile(rb"[\x20\x09-\x0D]")


@dataclass(frozen=True)
class Unit:
    """What the tokens are, how many make a window, and the sizes of digits, blocks and segments."""

    words: bool
    depth: int
    gram: int
    step: int
    segment: int

    def tokens(self, text: bytes) -> np.ndarray:
        if not self.words:
            return np.frombuffer(text, np.uint8)
        return np.concatenate([np.zeros(0, U), *(words_in([p])[0] for p in pieces(text))])

    def several(self, texts: list[bytes]) -> list[np.ndarray]:
        if not self.words:
            return [np.frombuffer(t, np.uint8) for t in texts]
        if len(texts) == 1:
            return [self.tokens(texts[0])]
        hashes, counts, _, _ = words_in(texts)
        return np.split(hashes, np.cumsum(counts)[:-1])

    def byte_bounds(self, text: bytes) -> tuple[np.ndarray, np.ndarray]:
        """First byte of every token, and the byte after it."""
        if not self.words:
            at = np.arange(len(text))
            return at, at + 1
        starts, ends, base = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], 0
        for p in pieces(text):
            _, _, ws, we = words_in([p])
            starts.append(ws - 1 + base)  # one separator stands before the first text
            ends.append(we - 1 + base)
            base += len(p)
        return np.concatenate(starts), np.concatenate(ends)


def byte_unit(depth: int = DEPTH, gram: int = GRAM) -> Unit:
    return Unit(False, depth, gram, STEP, SEGMENT)


def word_unit(depth: int = PASSAGE, gram: int = PASSAGE_GRAM) -> Unit:
    return Unit(True, depth, min(gram, depth), PASSAGE_STEP, SEGMENT // 4)


def pieces(text: bytes, most: int = 1 << 20):
    """A long text in pieces of about `most` bytes, cut at white space."""
    at = 0
    while at < len(text):
        cut = SPACE.search(text, at + most)
        end = cut.start() if cut else len(text)
        yield text[at:end]
        at = end


def words_in(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all words, words of each text, first byte and end of each word in the joined texts."""
    data, starts, _ = joined(texts)
    inside = ~space_table()[data]
    inside[[0, -1]] = False
    inside[starts - 1] = False
    ws, we = word_bounds(inside)
    counts = np.bincount(np.searchsorted(starts, ws, "right") - 1, minlength=len(texts))
    return word_hashes(data, ws, we), counts, ws, we


def sliding_least(h: np.ndarray, width: int) -> np.ndarray:
    """Least of every `width` neighbours, in two running minima over blocks of that width."""
    size = -(-len(h) // width) * width
    x = np.full(size, np.iinfo(np.uint64).max, np.uint64)
    x[: len(h)] = h
    x = x.reshape(-1, width)
    ahead = np.minimum.accumulate(x, 1).ravel()
    behind = np.minimum.accumulate(x[:, ::-1], 1)[:, ::-1].ravel()
    return np.minimum(behind[: len(h) - width + 1], ahead[width - 1 : len(h)])


class Prefix:
    """Hashes of substrings of one token array from its prefix sums: a polynomial over 64-bit integers, mixed."""

    up = down = np.zeros(0, U)

    def __init__(self, data: np.ndarray):
        n = len(data)
        if len(Prefix.up) <= n:  # powers are kept between arrays
            Prefix.up, Prefix.down = powers_of(BASE, n + 1), powers_of(pow(BASE, -1, 1 << 64), n + 1)
        self.total = np.zeros(n + 1, U)
        np.cumsum((data.astype(U) + U(1)) * Prefix.down[:n], out=self.total[1:])

    def every(self, k: int) -> np.ndarray:
        n = len(self.total) - 1
        return mixed((self.total[k:] - self.total[:-k]) * Prefix.up[: n - k + 1])

    def of(self, first: np.ndarray, k: int) -> np.ndarray:
        return mixed((self.total[first + k] - self.total[first]) * Prefix.up[first])


class Digits:
    """First digits of the suffixes of a token array."""

    def __init__(self, depth: int, gram: int):
        self.depth, self.gram = depth, gram

    def runs(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray):
        """Runs of suffixes with one first digit, within texts at starts..ends: text index, start, length, digit,
        hash of the span, whether the digit's gram occurs more than once in the span."""
        n, depth = len(data), self.depth
        long = ends - starts >= depth
        if n < depth or not long.any():
            return None
        h = Prefix(data).every(self.gram)
        width = depth - self.gram + 1
        m = sliding_least(h, width)
        at = np.unique(np.concatenate([np.flatnonzero(m[1:] != m[:-1]) + 1, starts[long], ends[long] - depth + 1]))
        at = at[at <= n - depth]
        following = np.append(at[1:], n - depth + 1)
        text = np.searchsorted(starts, at, "right") - 1
        own = at + depth <= ends[text]
        at, text = at[own], text[own]
        length = np.minimum(following[own], ends[text] - depth + 1) - at
        digit, view, size = m[at], memoryview(data).cast("B"), data.itemsize
        spans, again = np.empty(len(at), np.uint64), np.empty(len(at), bool)
        for i, (a, c) in enumerate(zip(at.tolist(), length.tolist(), strict=True)):
            spans[i] = xxhash.xxh3_64_intdigest(view[a * size : (a + c + depth - 1) * size])
            again[i] = np.count_nonzero(h[a : a + c - 1 + width] == digit[i]) > 1
        return text, at, length, digit, spans, again


def segments(texts: list[np.ndarray], depth: int, segment: int):
    """Groups of (text index, offset, tokens) of about `segment` tokens; a longer text is cut with depth - 1 tokens shared."""
    group, size = [], 0
    for i, t in enumerate(texts):
        if len(t) < depth:
            continue
        for offset in range(0, len(t) - depth + 1, segment):
            part = t[offset : offset + segment + depth - 1]
            if group and size + len(part) > 2 * segment:
                yield group
                group, size = [], 0
            group.append((i, offset, part))
            size += len(part)
    if group:
        yield group


def find_runs(docs: DataFrame, unit: Unit) -> DataFrame:
    """docs: doc, th (hash of the text), text. One row for each run."""

    @lean
    def run(batches):
        digits = Digits(unit.depth, unit.gram)
        for batch in batches:
            docs_of, th_of = batch.column("doc").to_numpy(), batch.column("th").to_numpy()
            for first, last, texts in text_blocks(batch.column("text")):
                doc, th = docs_of[first:last], th_of[first:last]
                for group in segments(unit.several(texts), unit.depth, unit.segment):
                    sizes = np.array([len(p) for _, _, p in group])
                    ends = np.cumsum(sizes)
                    found = digits.runs(np.concatenate([p for _, _, p in group]), ends - sizes, ends)
                    if found is None:
                        continue
                    part, at, length, digit, spans, again = found
                    which = np.array([g[0] for g in group])[part]
                    start = at - (ends - sizes)[part] + np.array([g[1] for g in group])[part]
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(doc[which]), pa.array(th[which]), pa.array(start.astype(np.int64)), pa.array(length.astype(np.int32)), pa.array(digit.view(np.int64)), pa.array(spans.view(np.int64)), pa.array(again)],
                        ["doc", "th", "start", "n", "digit", "span", "again"],
                    )

    return docs.mapInArrow(run, "doc bigint, th bigint, start bigint, n int, digit bigint, span bigint, again boolean")


def lists_of(column, *names: str):
    """For every row the arrays of the named fields of a list<struct> column, without an object for each element."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat, offsets = column.flatten(), column.offsets.to_numpy()
    offsets = offsets - offsets[0]
    fields = [flat.field(flat.type.get_field_index(n)).to_numpy(zero_copy_only=False) for n in names]
    for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
        yield [f[a:b] for f in fields]


def gathered(rows, names: list[str], kinds: list, most: int = 50_000):
    """Record batches of about `most` rows from tuples of arrays; None in an array's place is a column of nulls."""
    held, size = [], 0
    for part in rows:
        held.append(part)
        size += len(part[0])
        if size >= most:
            yield as_batch(held, names, kinds)
            held, size = [], 0
    if size:
        yield as_batch(held, names, kinds)


def as_batch(held, names, kinds):
    columns = []
    for i, kind in enumerate(kinds):
        columns.append(pa.concat_arrays([pa.nulls(len(p[0]), kind) if p[i] is None else pa.array(p[i], kind) for p in held]))
    return pa.RecordBatch.from_arrays(columns, names)


def in_rows(batches, column: str, *fields: str):
    """(doc, th, text as bytes, arrays of the fields) of every row; few texts are objects at a time."""
    for batch in batches:
        doc, th = batch.column("doc").to_numpy(), batch.column("th").to_numpy()
        lists = lists_of(batch.column(column), *fields)
        for first, last, texts in text_blocks(batch.column("text")):
            for i, raw in zip(range(first, last), texts, strict=True):
                yield int(doc[i]), int(th[i]), raw, next(lists)


def signed(h: np.ndarray) -> np.ndarray:
    return h.view(np.int64)


def hashes_at(tokens: np.ndarray, x: np.ndarray, k: int, segment: int) -> np.ndarray:
    """Hash of the k tokens from every x (in rising order); prefix sums of one segment at a time."""
    out = np.empty(len(x), U)
    cuts = np.flatnonzero(np.diff(x // segment)) + 1 if len(x) else []
    for part in np.split(np.arange(len(x)), cuts):
        if len(part):
            low, high = int(x[part[0]]), int(x[part[-1]]) + k
            out[part] = Prefix(tokens[low:high]).of(x[part] - low, k)
    return out


def blocks_of(doc: int, th: int, tokens: np.ndarray, runs, unit: Unit):
    """Rows (doc, th, at, size, digit, common, joint, times) of one text's open runs."""
    depth, step, n = unit.depth, unit.step, len(tokens)
    firsts, counts, of = [], [], []
    for s, length, digit, single in zip(*(r.tolist() for r in runs), strict=True):
        if single:
            here = np.arange(s, s + length)
            hashes = hashes_at(tokens, here, depth, unit.segment)
            values, first, inverse, count = np.unique(hashes, return_index=True, return_inverse=True, return_counts=True)
            k = len(values)
            yield np.full(k, doc), np.full(k, th), here[first], np.ones(k, np.int32), np.full(k, digit), signed(values), signed(values), np.minimum(count, 2).astype(np.int32)
            sure = np.concatenate([[False], count[inverse] > 1, [False]])
            edge = np.flatnonzero(sure[1:] != sure[:-1])
            a, b = edge[::2], edge[1::2]
            yield np.full(len(a), doc), np.full(len(a), th), s + a, (b - a).astype(np.int32), np.full(len(a), digit), None, None, np.full(len(a), 2, np.int32)
            continue
        grams = Prefix(tokens[s : s + length + depth - 1]).every(unit.gram)
        anchor = s + int(np.argmax(grams == U(digit & 0xFFFFFFFFFFFFFFFF)))
        first = s - (s - anchor) % step
        firsts.append(first)
        counts.append(-(-(s + length - first) // step))
        of.append(digit)
    if not firsts:
        return
    counts = np.array(counts)
    digit = np.repeat(np.array(of, np.int64), counts)
    inside = np.arange(len(digit)) - np.repeat(np.cumsum(counts) - counts, counts)
    x = np.repeat(np.array(firsts, np.int64), counts) + inside * step
    order = np.lexsort((digit, x))  # where a long text was cut, the runs on both sides hold the same block; it comes once
    x, digit = x[order], digit[order]
    once = np.append(True, (x[1:] != x[:-1]) | (digit[1:] != digit[:-1]))
    x, digit = x[once], digit[once]
    common = hashes_at(tokens, x + step - 1, depth - step + 1, unit.segment)
    whole = (x >= 0) & (x + step - 1 + depth <= n)
    # A block over the text's border is like no other one.
    joint = mixed(mixed(x.view(U) + U(doc & 0xFFFFFFFFFFFFFFFF)) ^ U(th & 0xFFFFFFFFFFFFFFFF))
    joint[whole] = hashes_at(tokens, x[whole], step - 1 + depth, unit.segment)
    k = len(x)
    yield np.full(k, doc), np.full(k, th), x, np.full(k, step, np.int32), digit, signed(common), signed(joint), np.ones(k, np.int32)


def cut_into_blocks(runs_with_text: DataFrame, unit: Unit) -> DataFrame:
    """doc, th, text, runs array<struct<start, n, digit, single>>. One row for each block: common and joint digit;
    in groups whose gram repeats within a window (single) a block is one suffix, and windows that occur twice in
    their own run come with times = 2 and as sure intervals (common is null)."""
    names = ["doc", "th", "at", "size", "digit", "common", "joint", "times"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32()]

    @lean
    def run(batches):
        rows = in_rows(batches, "runs", "start", "n", "digit", "single")
        yield from gathered((p for doc, th, raw, runs in rows for p in blocks_of(doc, th, unit.tokens(raw), runs, unit)), names, kinds)

    return runs_with_text.mapInArrow(run, "doc bigint, th bigint, at bigint, size int, digit bigint, common bigint, joint bigint, times int")


def single_suffixes(blocks_with_text: DataFrame, unit: Unit) -> DataFrame:
    """doc, th, text, blocks array<struct<at, size, digit, common>>. One row for each suffix of the blocks; blocks of one
    text can overlap, a suffix comes once for each digit and common digit."""

    def suffixes(doc, th, tokens, at, size, digit, common):
        last = len(tokens) - unit.depth
        low, high = np.maximum(at, 0), np.minimum(at + size, last + 1)
        count = np.maximum(high - low, 0)
        x = np.repeat(low, count) + np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        digit, common = np.repeat(digit, count), np.repeat(common, count)
        order = np.lexsort((common, digit, x))
        x, digit, common = x[order], digit[order], common[order]
        once = np.ones(len(x), bool)
        once[1:] = (x[1:] != x[:-1]) | (digit[1:] != digit[:-1]) | (common[1:] != common[:-1])
        x = x[once]
        return np.full(len(x), doc), np.full(len(x), th), x, digit[once], common[once], signed(hashes_at(tokens, x, unit.depth, unit.segment))

    @lean
    def run(batches):
        rows = in_rows(batches, "blocks", "at", "size", "digit", "common")
        yield from gathered((suffixes(doc, th, unit.tokens(raw), *blocks) for doc, th, raw, blocks in rows), ["doc", "th", "at", "digit", "common", "whole"], [pa.int64()] * 6)

    return blocks_with_text.mapInArrow(run, "doc bigint, th bigint, at bigint, digit bigint, common bigint, whole bigint")


def repeated_intervals(keyed: DataFrame, unit: Unit) -> DataFrame:
    """keyed: doc, th, text. (doc, th, a, b): every suffix that starts in [a, b) repeats elsewhere through the depth."""
    text = keyed.where(F.octet_length("text") >= (2 * unit.depth - 1 if unit.words else unit.depth))
    found = durable(find_runs(text, unit))
    shared = found.groupBy("digit").agg(F.count("*").alias("rows"), F.max("again").alias("any_again")).where("rows > 1 or any_again").select("digit")
    runs = durable(found.join(shared, "digit"))
    drop(found)
    spans = durable(runs.groupBy("digit", "span").agg(F.count("*").alias("copies"), F.min(F.struct("doc", "th", "start", "n")).alias("first"), F.max("again").alias("again")))
    whole = durable(runs.join(spans.where("copies > 1").select("digit", "span"), ["digit", "span"]).select("doc", "th", F.col("start").alias("a"), (F.col("start") + F.col("n")).alias("b")))
    drop(runs)

    kinds = spans.groupBy("digit").agg(F.count("*").alias("kinds"), F.max("again").alias("single"))
    open_runs = spans.join(kinds, "digit").where("kinds > 1 or (copies = 1 and single)").select("first.*", "digit", "single")
    by_doc = open_runs.groupBy("doc", "th").agg(F.collect_list(F.struct("start", "n", "digit", "single")).alias("runs"))
    by_doc = durable(by_doc)
    drop(spans)
    mark = F.xxhash64("doc", "th").alias("mark")
    candidates = keep_marked(text.select("doc", "th", "text", mark), "mark", bitmap_of(by_doc.select(mark), "mark"))
    texts = durable(candidates.join(by_doc, ["doc", "th"]).select("doc", "th", "text", "runs").dropDuplicates(["doc", "th"]))
    drop(by_doc)
    blocks = durable(cut_into_blocks(texts, unit))
    sure = blocks.where("common is null").select("doc", "th", F.col("at").alias("a"), (F.col("at") + F.col("size")).alias("b"))

    common = blocks.where("common is not null").groupBy("digit", "common").agg(F.sum("times").alias("all")).where("all > 1").select("digit", "common")
    alive = durable(blocks.join(common, ["digit", "common"]))
    joint = durable(alive.groupBy("digit", "common", "joint").agg(F.sum("times").alias("copies"), F.min(F.struct("doc", "th", "at", "size")).alias("first")))
    covered = alive.join(joint.where("copies > 1").select("digit", "common", "joint"), ["digit", "common", "joint"]).select("doc", "th", F.col("at").alias("a"), (F.col("at") + F.col("size")).alias("b"))
    certain = durable(covered.unionByName(sure))
    drop(blocks, alive)

    several = joint.groupBy("digit", "common").agg(F.count("*").alias("kinds")).where("kinds > 1").select("digit", "common")
    open_blocks = joint.join(several, ["digit", "common"]).select("first.*", "digit", "common")
    by_doc = open_blocks.groupBy("doc", "th").agg(F.collect_list(F.struct("at", "size", "digit", "common")).alias("blocks"))
    suffixes = durable(single_suffixes(texts.select("doc", "th", "text").join(by_doc, ["doc", "th"]), unit))
    drop(texts, joint)
    equal = suffixes.groupBy("digit", "common", "whole").agg(F.count("*").alias("copies")).where("copies > 1").drop("copies")
    alone = suffixes.join(equal, ["digit", "common", "whole"]).select("doc", "th", F.col("at").alias("a"), (F.col("at") + 1).alias("b"))
    return whole.unionByName(certain).unionByName(alone)


def cover(n: int, a: np.ndarray, b: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of tokens that windows starting in the intervals [a, b) cover, in a text of n tokens."""
    low, high = np.maximum(a, 0), np.minimum(b - 1 + depth, n)
    order = np.argsort(low, kind="stable")
    low, high = low[order], np.maximum.accumulate(high[order])
    new = np.append(True, low[1:] > high[:-1])
    return low[new], high[np.append(new[1:], True)]


def span_lists(keyed: DataFrame, unit: Unit) -> DataFrame:
    """doc, th, spans array<struct<a, b>>: one row for each text that holds a repeated window."""
    spans = repeated_intervals(keyed, unit)
    return durable(spans.distinct().groupBy("doc", "th").agg(F.collect_list(F.struct("a", "b")).alias("spans")))


def remove_repeats(docs: DataFrame, depth: int = DEPTH, gram: int = GRAM, replace_text: bool = False, unit: Unit | None = None, passages: Unit | None = None) -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256; with passages (a unit of words) also n_passage_words, the
    words covered by windows of that unit that occur anywhere else. With replace_text the columns of docs instead, with the
    remaining text (bytes of a character that was cut in two are dropped) and n_chars where there is such a column.
    unit: windows that are removed, of `depth` bytes where it is not given."""
    unit = unit or byte_unit(depth, gram)
    doc, th, mark, cut, told = (unused_name(docs, x) for x in ("doc", "th", "mark", "cut", "told"))
    columns = docs.columns if replace_text else ["doc_id", "text"]
    keyed = docs.select(*columns, F.coalesce(F.col("doc_id").cast("bigint"), F.lit(-(1 << 62))).alias(doc), F.xxhash64("text").alias(th))
    keyed = keyed.withColumn(mark, F.xxhash64(doc, th))
    sources = keyed.select(F.col(doc).alias("doc"), F.col(th).alias("th"), "text")
    lists = span_lists(sources, unit).withColumnRenamed("spans", cut)
    if passages:
        lists = durable(lists.join(span_lists(sources, passages).withColumnRenamed("spans", told), ["doc", "th"], "full"))
    else:
        lists = lists.withColumn(told, F.col(cut))
    lists = lists.withColumnsRenamed({"doc": doc, "th": th})
    bitmap = bitmap_of(lists.select(F.xxhash64(doc, th).alias("mark")), "mark")
    joined_lists = keep_marked(keyed, mark, bitmap).join(lists, [doc, th], "left").select(*columns, cut, told)
    sent = docs.sparkSession.sparkContext.broadcast(bitmap)
    more = ", n_passage_words bigint" if passages else ""
    out_schema = docs.schema if replace_text else "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string" + more
    arrow_names = docs.columns

    def cut_out(raw: bytes, a: np.ndarray, b: np.ndarray) -> tuple[bytes, int]:
        starts, ends = unit.byte_bounds(raw) if unit.words else (None, None)
        low, high = cover(len(raw) if starts is None else len(starts), a, b, unit.depth)
        if starts is not None:
            low, high = starts[low], ends[high - 1]
        edges = [0, *(int(x) for ab in zip(low, high, strict=True) for x in ab), len(raw)]
        return b"".join(raw[x:y] for x, y in zip(edges[::2], edges[1::2], strict=True)), len(low)

    def untouched(batches):
        """Of all rows those whose bit is not set; in the same worker as what follows."""
        nothing = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))
        for batch in batches:
            rest = batch.filter(pa.array(~marked(batch.column(mark).to_numpy(), sent.value)))
            yield pa.RecordBatch.from_arrays([*(rest.column(c) for c in columns), *[pa.nulls(rest.num_rows, nothing)] * 2], [*columns, cut, told])

    @lean
    def run(batches):
        for batch in batches:
            removed, noted = lists_of(batch.column(cut), "a", "b"), lists_of(batch.column(told), "a", "b")
            sizes, kept_sizes, spans, digests, noted_words, fresh = [], [], [], [], [], []
            for _, _, texts in text_blocks(batch.column("text")):
                for raw in texts:
                    (a, b), (c, d) = next(removed), next(noted)
                    kept, n_spans = cut_out(raw, a, b) if len(a) else (raw, 0)
                    if replace_text:
                        fresh.append(kept.decode("utf-8", "ignore") if n_spans else None)
                        continue
                    sizes.append(len(raw))
                    kept_sizes.append(len(kept))
                    spans.append(n_spans)
                    digests.append(hashlib.sha256(kept).hexdigest())
                    if passages:
                        low, high = cover(len(passages.tokens(raw)), c, d, passages.depth) if len(c) else (np.zeros(0), np.zeros(0))
                        noted_words.append(int((high - low).sum()))
            if not replace_text:
                n = np.array(sizes, np.int64)
                out = [batch.column("doc_id").cast(pa.int64()), pa.array(n), pa.array(n - np.array(kept_sizes, np.int64)), pa.array(spans, pa.int64()), pa.array(digests, pa.string())]
                names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
                if passages:
                    out.append(pa.array(noted_words, pa.int64()))
                    names.append("n_passage_words")
                yield pa.RecordBatch.from_arrays(out, names)
                continue
            changed = pa.array([f is not None for f in fresh])
            values = {"text": pa.array(fresh, batch.column("text").type), "n_chars": [None if f is None else len(f) for f in fresh]}
            out = []
            for c in arrow_names:
                old = batch.column(c)
                new = pa.array(values[c], old.type) if c in values else None
                out.append(old if new is None else pc.if_else(changed, new, old))
            yield pa.RecordBatch.from_arrays(out, arrow_names)

    rest = keyed.select(*columns, mark).mapInArrow(lambda batches: run(untouched(batches)), out_schema)
    return joined_lists.mapInArrow(run, out_schema).unionAll(rest)
