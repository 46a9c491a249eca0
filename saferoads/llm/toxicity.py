"""Toxicity by subword-bag embeddings averaged into a linear softmax, trained jointly in numpy.

A word is the bag of its character 3-, 4- and 5-grams (with word ends) and itself, each hashed to a row of one
embedding table; a block of consecutive words is the mean of its words; a softmax over two classes reads the mean.
A disguised or misspelt word shares most of its grams with the known one. A label belongs to a document, but the
words that earn it may stand in one block, so after a first pass only the strongest block of a toxic document
counts as toxic. The score of a document is the strongest block's margin, calibrated on sampled documents that
the table was not fitted to. Rows are scored where they are: nothing is shuffled.

The fit uses a bounded sample of labelled rows: at most `per_class` toxic and three times as many clean
ones, least in a hash of doc_id, texts of at most `longest` bytes; of a clean one, a passage of 4 KB. Null or empty texts get the score of a document without words. A document
without a label, or with a null one, is only scored. No labelled row of one class, or no word in the texts of one: every
score is the share of toxic ones (0 if there is none at all). Rows of one doc_id: one of them is learned from, all are
scored. Ties among sampled rows go to the lesser doc_id. Other columns may have any name.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from saferoads.llm.blocks import gram_buckets, joined, lean, letter_table, lowered_latin, split_of, text_blocks, word_bounds, word_hashes

BITS, GRAMS, WORDS, DIM = 16, (3, 4, 5), 4, 8
THRESHOLD = 0.3


def words_of(texts: list[bytes]):
    """Bytes with everything outside words blanked, bounds of the words, and each word's document."""
    data, starts, _ = joined(texts)
    data = lowered_latin(data)
    inside = letter_table()[data]
    inside[[0, -1]] = False
    shown = np.where(inside, data, np.uint8(32))
    ws, we = word_bounds(inside)
    return shown, ws, we, np.searchsorted(starts, ws, "right") - 1


def block_ids(doc: np.ndarray, n_docs: int) -> tuple[np.ndarray, np.ndarray]:
    """Block of each word, and the document of each block; no block spans documents."""
    first = np.searchsorted(doc, np.arange(n_docs + 1))
    counts = np.diff(first)
    blocks = -(-counts // WORDS)
    base = np.concatenate([[0], np.cumsum(blocks)])
    return base[doc] + (np.arange(len(doc)) - first[doc]) // WORDS, np.repeat(np.arange(n_docs), blocks)


def vocabulary(texts: list[bytes]):
    """Table rows of the subwords of every distinct word, their bounds, the distinct word of each word in the
    texts, and each word's document."""
    shown, ws, we, doc = words_of(texts)
    hashes = word_hashes(shown, ws, we)
    _, first, word = np.unique(hashes, return_index=True, return_inverse=True)
    ws, we = ws[first], we[first]
    rows, owner = [(hashes[first] >> np.uint64(64 - BITS)).astype(np.int32) + (1 << BITS)], [np.arange(len(ws))]
    for n in GRAMS:
        count = np.maximum(we - ws + 3 - n, 0)
        at = np.repeat(ws - 1 - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(count.sum())
        rows.append(gram_buckets(shown, n, BITS)[at].astype(np.int32))
        owner.append(np.repeat(np.arange(len(ws)), count))
    owner = np.concatenate(owner)
    order = np.argsort(owner, kind="stable")
    return np.concatenate(rows)[order], np.searchsorted(owner[order], np.arange(len(ws) + 1)), word, doc


def spread(bounds: np.ndarray, chosen: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions bounds[c] to bounds[c + 1] for every c of chosen, and the index of that c."""
    sizes = bounds[chosen + 1] - bounds[chosen]
    which = np.repeat(np.arange(len(chosen)), sizes)
    return np.arange(len(which)) + (bounds[chosen] - np.concatenate([[0], np.cumsum(sizes)[:-1]]))[which], which


def fit_table(texts: list[bytes], labels: np.ndarray, seed: int = 7, rounds: int = 6, batch: int = 768, rate: float = 0.05, steps: int = 25, drop: float = 0.5) -> np.ndarray:
    """Margin of every row of the table (embedding times the difference of the classes' weights), last the bias."""
    rng = np.random.default_rng(seed)
    size = 2 << BITS
    table, top, bias = rng.normal(0, 0.1, (size, DIM)).astype(np.float32), np.zeros((DIM, 2), np.float32), np.zeros(2, np.float32)
    top[:] = rng.normal(0, 0.3, top.shape)
    state = [[np.zeros_like(x), np.zeros_like(x)] for x in (table, top, bias)]
    rows, of_word, word, doc = vocabulary(texts)
    in_block, doc_of = block_ids(doc, len(texts))
    n_blocks = len(doc_of)
    if not n_blocks:
        return np.zeros(size + 1, np.float32)
    bounds = np.searchsorted(in_block, np.arange(n_blocks + 1))
    subs, words = np.diff(of_word), np.diff(bounds)
    table[np.bincount(rows, minlength=size) == 0] = 0
    truth = labels[doc_of]
    use, step = np.ones(n_blocks, bool), 0
    for turn in range(rounds):
        if turn >= 2:
            of_words = np.add.reduceat((table @ (top[:, 1] - top[:, 0]))[rows], of_word[:-1]) / subs
            margin = np.add.reduceat(of_words[word], bounds[:-1]) / words
            best = np.full(len(texts), -np.inf)
            np.maximum.at(best, doc_of, margin)
            use = (truth == 0) | (margin >= best[doc_of])
        positive = np.flatnonzero(use & (truth == 1))
        negative = np.flatnonzero(use & (truth == 0))
        if not len(positive) or not len(negative):  # no text of one class has a word
            return np.zeros(size + 1, np.float32)
        rng.shuffle(negative)
        for k in range(max(-(-len(negative) // (batch * 7)), steps)):
            some = np.arange(k * batch * 7, min((k + 1) * batch * 7, k * batch * 7 + len(negative))) % len(negative)
            chosen = np.concatenate([negative[some], rng.choice(positive, -(-len(some) // 7))])
            token, block = spread(bounds, chosen)
            flat, of_token = spread(of_word, word[token])
            r, b = rows[flat], block[of_token]
            w = (1 / (subs[word[token]] * words[chosen][block]))[of_token]
            kept = rng.random(len(r)) >= drop  # no subword is relied on alone
            r, b, w = r[kept], b[kept], w[kept] / (1 - drop)
            hidden = np.stack([np.bincount(b, table[r, d] * w, len(chosen)) for d in range(DIM)], 1).astype(np.float32)
            logits = hidden @ top + bias
            p = np.exp(logits - logits.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(chosen)), truth[chosen]] -= 1
            p /= len(chosen)
            back = p @ top.T
            grads = (np.stack([np.bincount(r, back[b, d] * w, size) for d in range(DIM)], 1).astype(np.float32), hidden.T @ p, p.sum(0))
            step += 1
            for x, g, (m, v) in zip((table, top, bias), grads, state, strict=True):
                m += 0.1 * (g - m)
                v += 0.02 * (g * g - v)
                x -= rate * (1 - turn / rounds) * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.98**step)) + 1e-8)
    return np.append(table @ (top[:, 1] - top[:, 0]), bias[1] - bias[0]).astype(np.float32)


def margins(texts: list[bytes], model: np.ndarray) -> np.ndarray:
    """The strongest block's margin of each text; -inf where there is no word."""
    shown, ws, we, doc = words_of(texts)
    out = np.full(len(texts), -np.inf)
    if not len(ws):
        return out
    total = model[(word_hashes(shown, ws, we) >> np.uint64(64 - BITS)).astype(np.int64) + (1 << BITS)].astype(np.float64)
    count = np.ones(len(ws), np.int64)
    for n in GRAMS:
        sums = np.concatenate([[0.0], np.cumsum(model[gram_buckets(shown, n, BITS)], dtype=np.float64)])
        last = np.maximum(we + 2 - n, ws - 1)
        inside = np.minimum(last, len(sums) - 1)
        total += sums[inside] - sums[np.minimum(ws - 1, inside)]
        count += last - (ws - 1)
    in_block, doc_of = block_ids(doc, len(texts))
    first = np.searchsorted(in_block, np.arange(len(doc_of)))
    block = np.add.reduceat(total / count, first) / np.diff(np.append(first, len(doc))) + model[-1]
    np.maximum.at(out, doc_of, block)
    return out


def calibrate(margin: np.ndarray, labels: np.ndarray, share: float) -> tuple[float, float]:
    """Logistic fit (slope, offset); the classes weigh as in the whole of the labels."""
    x = np.maximum(margin, -30.0)
    center, width = x.mean(), max(x.std(), 1e-6)
    z = np.stack([(x - center) / width, np.ones(len(x))], 1)
    weight = np.where(labels == 1, share / max(labels.mean(), 1e-9), (1 - share) / max(1 - labels.mean(), 1e-9))
    w = np.array([1.0, math.log(max(share, 1e-6) / max(1 - share, 1e-6))])
    for _ in range(30):
        p = 1 / (1 + np.exp(-z @ w))
        slope = z.T @ (weight * (p - labels)) + 0.1 * w * [1, 0]
        bend = z.T @ (z * (weight * p * (1 - p))[:, None]) + np.diag([0.1, 1e-6])
        move = np.linalg.solve(bend, slope)
        w -= move / max(1.0, np.abs(move).max())
    return float(w[0] / width), float(w[1] - w[0] * center / width)


def passage(text: bytes, seed: int, most: int = 4096) -> bytes:
    """A stretch of a clean text for the fit: any of its blocks is an example as good as another."""
    at = int(np.random.default_rng(seed).integers(0, max(len(text) - most, 0) + 1))
    return text[at : at + most]


def train(docs: DataFrame, labels: DataFrame, per_class: int = 900, longest: int = 1 << 16, fold: tuple[int, int] = (4, 2)) -> dict:
    """labels: doc_id, toxic. Rows of the held-out fold (crc32 of doc_id modulo fold[0] equal to fold[1]) stay out."""
    mine = F.crc32(F.col("doc_id").cast("string")) % fold[0] != fold[1]
    known = labels.where(mine & F.col("toxic").isNotNull()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    counts = {r["toxic"]: r["n"] for r in known.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    n1, n0 = counts.get(1, 0), counts.get(0, 0)
    share = n1 / max(n0 + n1, 1)
    picked = [known.where(F.col("toxic") == c).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class * (1 + 2 * (c == 0))) for c in (0, 1)]
    rows = (
        docs.select("doc_id", "text").where(F.octet_length("text") <= longest)
        .join(F.broadcast(picked[0].union(picked[1])), "doc_id")  # at most 4 * per_class ids
        .dropDuplicates(["doc_id"]).collect()
    )
    rows.sort(key=lambda r: r["doc_id"])
    texts, truth = [r["text"].encode() for r in rows], np.array([r["toxic"] for r in rows], np.int64)
    if not len(truth) or truth.min() == truth.max():
        return {"model": None, "share": share}
    aside = np.arange(len(texts)) % 4 == 3
    if len(set(truth[~aside])) < 2 or len(set(truth[aside])) < 2:
        aside[:] = False
    fitted = np.flatnonzero(~aside)
    model = fit_table([texts[i] if truth[i] else passage(texts[i], int(i)) for i in fitted], truth[fitted])
    if not model.any():
        return {"model": None, "share": share}
    tried = np.flatnonzero(aside) if aside.any() else fitted
    slope, offset = calibrate(margins([texts[i] for i in tried], model), truth[tried], share)
    return {"model": model, "share": share, "slope": slope, "offset": offset}


def scores(column, trained: dict) -> np.ndarray:
    if trained["model"] is None:
        return np.full(len(column), float(trained["share"]))
    out = np.empty(len(column))
    for a, b, texts in text_blocks(column):
        m = np.maximum(margins(texts, trained["model"]), -30.0)
        out[a:b] = 1 / (1 + np.exp(-np.clip(trained["slope"] * m + trained["offset"], -60, 60)))
    return out


def score(docs: DataFrame, trained: dict, fold: tuple[int, int] = (4, 2)) -> DataFrame:
    """doc_id, held_out, score, predicted for every row."""
    sent = docs.sparkSession.sparkContext.broadcast(trained)  # a table of fixed size

    @lean
    def run(batches):
        for batch in batches:
            ids = batch.column("doc_id")
            s = scores(batch.column("text"), sent.value)
            held = split_of(ids.to_pylist(), fold[0]) == fold[1]
            yield pa.RecordBatch.from_arrays([ids.cast(pa.int64()), pa.array(held), pa.array(s), pa.array((s >= THRESHOLD).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, held_out boolean, score double, predicted int")


def drop_toxic(docs: DataFrame, trained: dict) -> DataFrame:
    """Rows whose score is below the threshold, with all their columns."""
    sent = docs.sparkSession.sparkContext.broadcast(trained)

    @lean
    def run(batches):
        for batch in batches:
            keep = scores(batch.column("text"), sent.value) < THRESHOLD
            yield batch.filter(pa.array(keep))

    return docs.mapInArrow(run, docs.schema)
