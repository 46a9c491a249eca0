"""Word-level language labels by a linear-chain conditional random field, for code-switched text.

Features of a word: its character 2-, 3- and 4-grams, of which those at the word's ends are affixes, and the word itself
as a lexicon entry; each is hashed to a row with one weight for each language. Transitions between the labels of
neighbouring words are learned with them, on chains spliced from sampled documents of different languages so that
switches occur. Forward-backward gives every word's posterior; a document's language is the one of largest summed
posterior, its score that sum's share. A text is one chain. Its blocks of CHAIN words run side by side in numpy: the
product of a block's steps is a small matrix, and these matrices carry the messages from block to block, exactly.

The fit uses a bounded sample: `per_language` documents of each language, least in a hash of doc_id, of texts of at
most `longest` bytes. Scoring covers whole texts. Texts that are null or have no letter are `und` with score 0; so is
every text if there is no labelled row. An empty table gives no rows. Ties go to the language that is first in the alphabet,
those among sampled rows to the lesser doc_id. Of rows of one doc_id one is learned from; all are labelled. Other columns may
have any name.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from saferoads.llm.blocks import gram_buckets, joined, lean, letter_table, lowered_latin, split_of, text_blocks, word_bounds, word_hashes

BITS, GRAMS, CHAIN = 16, (2, 3, 4), 64
LETTER = re.compile(r"[^\W\d_]")


def word_rows(texts: list[bytes]):
    """Blanked bytes, word bounds and each word's document."""
    data, starts, _ = joined(texts)
    data = lowered_latin(data)
    inside = letter_table()[data]
    inside[[0, -1]] = False
    shown = np.where(inside, data, np.uint8(32))
    ws, we = word_bounds(inside)
    return shown, ws, we, np.searchsorted(starts, ws, "right") - 1


def emissions(texts: list[bytes], weights: np.ndarray):
    """Score of every label for every word (mean of its features' weights, scaled by the root of their number), and
    each word's document."""
    shown, ws, we, doc = word_rows(texts)
    if not len(ws):
        return np.zeros((0, weights.shape[1]), np.float32), doc
    total = weights[(word_hashes(shown, ws, we) >> np.uint64(64 - BITS)).astype(np.int64) + (1 << BITS)].astype(np.float64)
    count = np.ones(len(ws))
    for n in GRAMS:
        rows = weights[gram_buckets(shown, n, BITS)]
        sums = np.zeros((len(rows) + 1, weights.shape[1]))
        np.cumsum(rows, axis=0, dtype=np.float64, out=sums[1:])
        last = np.minimum(np.maximum(we + 2 - n, ws - 1), len(rows))
        total += sums[last] - sums[np.minimum(ws - 1, last)]
        count += np.maximum(last - (ws - 1), 0)
    return (total / np.sqrt(count)[:, None]).astype(np.float32), doc


def chains(doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Words as a table of blocks by positions: index of each cell's word, and whether there is one."""
    first = np.flatnonzero(np.concatenate([[True], doc[1:] != doc[:-1]])) if len(doc) else np.zeros(0, np.int64)
    sizes = np.diff(np.append(first, len(doc)))
    pieces = -(-sizes // CHAIN)
    start = np.repeat(first, pieces) + CHAIN * (np.arange(pieces.sum()) - np.repeat(np.cumsum(pieces) - pieces, pieces))
    length = np.minimum(CHAIN, np.repeat(first + sizes, pieces) - start)
    cell = start[:, None] + np.arange(CHAIN)[None, :]
    there = np.arange(CHAIN)[None, :] < length[:, None]
    return np.where(there, cell, 0), there


def scaled(x: np.ndarray) -> np.ndarray:
    return x / x.sum(-1, keepdims=True)


def messages(score: np.ndarray, there: np.ndarray, moves: np.ndarray, text: np.ndarray):
    """What reaches every block from the words before it (the labels' weights at the last of them) and from those after it;
    text: of each block, in order. A block that begins a text starts from its own words alone."""
    n, length, k = score.shape
    likely = np.exp(score - score.max(2, keepdims=True))
    step = np.exp(moves - moves.max())
    first = np.append(True, text[1:] != text[:-1])
    through = np.where(first[:, None, None], 1.0, step[None]) * likely[:, 0, None, :]
    for t in range(1, length):
        on = there[:, t]
        if not on.any():
            break
        moved = (through[on] @ step) * likely[on, t, None, :]
        through[on] = moved / moved.sum((1, 2), keepdims=True)
    heads = np.flatnonzero(first)
    sizes = np.diff(np.append(heads, n))
    before, after, leaving = np.full((n, k), 1 / k), np.ones((n, k)), np.empty((n, k))
    for j in range(int(sizes.max())):
        here = heads[sizes > j] + j
        if j:
            before[here] = leaving[here - 1]
        leaving[here] = scaled(np.einsum("ni,nij->nj", before[here], through[here]))
    for j in range(int(sizes.max()) - 1, 0, -1):
        here = heads[sizes > j] + j
        after[here - 1] = scaled(np.einsum("nij,nj->ni", through[here], after[here]))
    return first, before, after


def forward_backward(score: np.ndarray, there: np.ndarray, moves: np.ndarray, with_moves: bool = True, reached: tuple | None = None):
    """score: chains x positions x labels. Posteriors of labels, and summed posteriors of moves (within the rows) if wanted.
    reached: the messages of rows that are blocks of longer chains."""
    likely = np.exp(score - score.max(2, keepdims=True))
    likely[~there] = 1.0
    step = np.exp(moves - moves.max())
    n, length, k = score.shape
    ahead, behind = np.empty((length, n, k)), np.empty((length, n, k))
    ahead[0] = scaled(likely[:, 0])
    if reached:
        first, before, after = reached
        ahead[0] = np.where(first[:, None], ahead[0], scaled((before @ step) * likely[:, 0]))
    for t in range(1, length):
        a = (ahead[t - 1] @ step) * likely[:, t]
        ahead[t] = np.where(there[:, t, None], a / a.sum(1, keepdims=True), ahead[t - 1])
    behind[-1] = after if reached else 1.0
    pairs = np.zeros((k, k))
    for t in range(length - 2, -1, -1):
        next_ = likely[:, t + 1] * behind[t + 1]
        b = next_ @ step.T
        behind[t] = np.where(there[:, t + 1, None], scaled(b), behind[t + 1])
        if not with_moves:
            continue
        joint = ahead[t][:, :, None] * step[None] * next_[:, None, :]
        joint /= joint.sum((1, 2), keepdims=True)
        pairs += joint[there[:, t + 1]].sum(0)
    post = ahead * behind
    return (post / post.sum(2, keepdims=True)).transpose(1, 0, 2), pairs


def fit(texts: list[bytes], labels: np.ndarray, k: int, seed: int = 5, rounds: int = 4, batch: int = 64) -> tuple[np.ndarray, np.ndarray]:
    """Weights of the feature rows and of the moves, by stochastic gradient with forward-backward."""
    rng = np.random.default_rng(seed)
    weights, moves = np.zeros((2 << BITS, k), np.float32), np.zeros((k, k))
    shown, ws, we, doc = word_rows(texts)
    if not len(ws):
        return weights, moves
    features = [(word_hashes(shown, ws, we) >> np.uint64(64 - BITS)).astype(np.int64) + (1 << BITS)]
    owner = [np.arange(len(ws))]
    for n in GRAMS:
        count = np.maximum(np.minimum(we + 2 - n, len(shown) - n + 1) - (ws - 1), 0)
        at = np.repeat(ws - 1 - (np.cumsum(count) - count), count) + np.arange(count.sum())
        features.append(gram_buckets(shown, n, BITS)[at].astype(np.int64))
        owner.append(np.repeat(np.arange(len(ws)), count))
    features, owner = np.concatenate(features), np.concatenate(owner)
    order = np.argsort(owner, kind="stable")
    features, bounds = features[order].astype(np.int32), np.searchsorted(owner[order], np.arange(len(ws) + 1))
    scale = 1 / np.sqrt(np.diff(bounds))
    truth = labels[doc]
    # Pieces of 4 to 24 words of one document each; chains are filled with pieces of random documents.
    cuts = np.unique(np.concatenate([[0, len(ws)], np.flatnonzero(doc[1:] != doc[:-1]) + 1, np.cumsum(rng.integers(4, 25, len(ws) // 4 + 1))]))
    cuts = cuts[cuts <= len(ws)]
    pieces = np.stack([cuts[:-1], cuts[1:]], 1)
    for turn in range(rounds):
        rng.shuffle(pieces)
        sequence = np.concatenate([np.arange(a, b) for a, b in pieces])
        sequence = sequence[: len(sequence) // CHAIN * CHAIN] if len(sequence) >= CHAIN else np.resize(sequence, CHAIN)
        table = sequence.reshape(-1, CHAIN)
        speed = 0.5 * (1 - turn / rounds)
        for start in range(0, len(table), batch):
            words = table[start : start + batch].ravel()
            sizes = bounds[words + 1] - bounds[words]
            of = np.repeat(np.arange(len(words)), sizes)
            f = features[np.arange(len(of)) + (bounds[words] - (np.cumsum(sizes) - sizes))[of]]
            w = scale[words][of]
            score = np.stack([np.bincount(of, weights[f, j] * w, len(words)) for j in range(k)], 1).reshape(-1, CHAIN, k)
            there = np.ones(score.shape[:2], bool)
            post, pairs = forward_backward(score, there, moves)
            gold = truth[words].reshape(-1, CHAIN)
            wrong = post.reshape(-1, k)
            wrong[np.arange(len(words)), gold.ravel()] -= 1
            for j in range(k):
                weights[:, j] -= (speed * np.bincount(f, wrong[of, j] * w, len(weights))).astype(np.float32)
            seen = np.zeros((k, k))
            np.add.at(seen, (gold[:, :-1].ravel(), gold[:, 1:].ravel()), 1)
            moves += speed * 0.2 * (seen - pairs) / len(words) * k
    return weights, moves


def train(docs: DataFrame, per_language: int = 150, longest: int = 32_768, fold: tuple[int, int] = (4, 2)) -> dict:
    """Learns from text and lang of the rows outside the held-out fold."""
    mine = F.crc32(F.col("doc_id").cast("string")) % fold[0] != fold[1]
    known = docs.where(mine & F.col("lang").isNotNull() & (F.octet_length("text") <= longest)).select("doc_id", "lang", F.xxhash64("doc_id").alias("h"), "text")
    # The least hashes of every language without a task for each: first within slices, then among the slices' picks.
    sliced = known.withColumn("slice", F.pmod("h", F.lit(64)))
    by = Window.partitionBy("lang", "slice").orderBy("h", "doc_id")
    few = sliced.select("lang", "slice", "h", "doc_id").withColumn("r", F.row_number().over(by)).where(F.col("r") <= per_language)
    top = few.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy("h", "doc_id"))).where(F.col("r") <= per_language)
    rows = known.join(F.broadcast(top.select("doc_id", "lang")), ["doc_id", "lang"]).select("doc_id", "lang", "text").dropDuplicates(["doc_id"]).collect()
    rows.sort(key=lambda r: (r["doc_id"], r["lang"]))
    names = sorted({r["lang"] for r in rows})
    if not names:
        return {"names": [], "weights": None, "moves": None}
    weights, moves = fit([r["text"].encode() for r in rows], np.array([names.index(r["lang"]) for r in rows]), len(names))
    return {"names": names, "weights": weights, "moves": moves}


def label_words(texts: list[bytes], model: dict) -> tuple[np.ndarray, np.ndarray]:
    """Posterior of every label for every word, and each word's document."""
    score, doc = emissions(texts, model["weights"])
    if not len(doc):
        return np.zeros((0, len(model["names"]))), doc
    cell, there = chains(doc)
    out = np.empty((len(doc), len(model["names"])))
    table = score[cell]
    reached = messages(table, there, model["moves"], doc[cell[:, 0]])
    post, _ = forward_backward(table, there, model["moves"], with_moves=False, reached=reached)
    out[cell[there]] = post[there]
    return out, doc


def predict(docs: DataFrame, model: dict, fold: tuple[int, int] = (4, 2)) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # tables of fixed size

    @lean
    def run(batches):
        names = np.array([*sent.value["names"], "und"], object)
        k = len(names) - 1
        for batch in batches:
            pick, score = np.full(batch.num_rows, k), np.zeros(batch.num_rows)
            for a, b, texts in text_blocks(batch.column("text")) if k else ():
                lettered = np.array([LETTER.search(t.decode("utf-8", "replace")) is not None for t in texts], bool)
                post, doc = label_words(texts, sent.value)
                sums = np.stack([np.bincount(doc, post[:, j], b - a) for j in range(k)], 1) if len(doc) else np.zeros((b - a, k))
                pick[a:b] = np.where(lettered, sums.argmax(1), k)
                score[a:b] = np.where(lettered, sums.max(1) / np.maximum(sums.sum(1), 1e-9), 0.0)
            ids = batch.column("doc_id")
            held = split_of(ids.to_pylist(), fold[0]) == fold[1]
            yield pa.RecordBatch.from_arrays([ids.cast(pa.int64()), pa.array(held), pa.array(names[pick].tolist(), pa.string()), pa.array(np.clip(score, 0, 1))], ["doc_id", "held_out", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, held_out boolean, lang_pred string, score double")


def word_labels(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, word_index, lang_pred, score for every word of every text."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    @lean
    def run(batches):
        names = np.array(sent.value["names"], object)
        for batch in batches:
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
            for a, b, texts in text_blocks(batch.column("text")) if len(names) else ():
                post, doc = label_words(texts, sent.value)
                if len(doc):
                    index = np.arange(len(doc)) - np.searchsorted(doc, doc)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[a:b][doc], pa.int64()), pa.array(index), pa.array(names[post.argmax(1)].tolist(), pa.string()), pa.array(post.max(1))], ["doc_id", "word_index", "lang_pred", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, word_index bigint, lang_pred string, score double")
