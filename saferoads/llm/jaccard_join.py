"""Jaccard join of word n-gram sets by a partition of the hashed universe and the pigeonhole principle.

Sets of sizes a and b that reach the similarity differ in at most H = (1 - t) / (1 + t) * (a + b) elements. Sizes fall
into bands that double; a pair meets in the band of its larger set. The band cuts the universe into m segments by hash
and indexes every set's exact subsets: m - H segments at least are equal. Segments of short sets would be empty too
often; where that costs more (`allocate`), the sets of a band are indexed whole, with the neighbourhoods of one deletion
and, where the bound allows more differences, of as many.

More segments than the bound asks for leave room for choice. A set keeps its H + 1 + e segments of most elements (an
order both sides of a pair know; e is one for all sets of a band), so linked sets share e + 1 buckets at least. Sets with fewer shared buckets are
out, and each set drops its e most frequent buckets: of e + 1 shared ones the rarest is dropped by neither side.

Equal sets are one class from the start. Links are verified exactly on the texts, in rounds: every bucket names a
leader, its members are compared with it, and linked classes join a component; a last round compares all pairs of
a bucket that are still in different components, those of large buckets in blocks. A pair inside a component needs no
comparison, so a group of thousands of copies costs about one comparison each, and no link between components is lost.

Null or empty texts have an empty set and link with nothing. Rows without doc_id take no part: their component is null.
Rows of one doc_id are one vertex: it has the links of all their sets. A pair exactly at the similarity is linked. Texts of
any length are sets of their n-grams like others. Other columns of docs may have any name. An empty table gives no rows.
"""

from __future__ import annotations

import itertools
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from saferoads.llm.bitmap import bitmap_of, keep_marked
from saferoads.llm.blocks import joined, lean, mixed, space_table, text_blocks, unused_name, word_bounds, word_hashes
from saferoads.plans.components import connected_components
from saferoads.plans.runtime import drop, durable

WORDS, PERCENT = 4, 85
U = np.uint64


def most_differences(a, b, percent: int):
    return (100 - percent) * (a + b) // (100 + percent)


def largest_partner(a, percent: int):
    return 100 * a // percent


def spare(h):
    return h // 8


def band_spare(band: int, percent: int) -> int:
    """e of a band: both sides of a pair have to drop the same number of buckets, so it cannot depend on the set."""
    largest = (2 << band) - 1
    return spare(most_differences(largest, largest, percent))


def allocate(band: int, percent: int) -> tuple[int, bool]:
    """Segments of a band (sizes 2^band to 2^(band + 1) - 1), and whether its sets are indexed whole with their deletion
    neighbourhoods instead. By cost: rows of the largest set, and the risk that the smallest one has too few segments with
    elements, so that empty ones, which all sets share, would have to stand in."""
    largest, smallest = (2 << band) - 1, 1 << band
    h = most_differences(largest, largest, percent)
    m = h + 1 + band_spare(band, percent)
    if band > 6:
        return m, False  # a neighbourhood would have millions of rows
    low = most_differences(smallest, largest_partner(smallest, percent), percent)
    lacking = m - (low + 1 + band_spare(band, percent)) + 1
    risk = min(1.0, math.comb(m, lacking) * math.exp(-smallest / m * lacking))
    around = sum(math.comb(largest, j) for j in range(h + 1))
    return m, around <= m + 1e4 * risk


def ngram_sets(texts: list[bytes], words: int):
    """Distinct n-gram hashes of all texts in order of (text, hash), and the bounds of each text's."""
    data, starts, _ = joined(texts)
    data = data + ((data >= 65) & (data <= 90)).astype(np.uint8) * np.uint8(32)
    inside = ~space_table()[data]
    inside[[0, -1]] = False
    inside[starts - 1] = False
    ws, we = word_bounds(inside)
    h = word_hashes(data, ws, we)
    doc = np.searchsorted(starts, ws, "right") - 1
    count = np.bincount(doc, minlength=len(texts))
    first = np.concatenate([[0], np.cumsum(count)[:-1]])
    grams = np.zeros(max(len(h) - words + 1, 0), U)
    for k in range(words):
        grams = mixed(grams + h[k : k + len(grams)] + U(k + 1))
    whole = doc[: len(grams)] == doc[words - 1 : words - 1 + len(grams)]
    of, grams = doc[: len(grams)][whole], grams[whole]
    short = np.flatnonzero((count > 0) & (count < words))
    if len(short):
        extra = np.zeros(len(short), U)
        for k in range(words - 1):
            has = count[short] > k
            extra[has] = mixed(extra[has] + h[first[short[has]] + k] + U(k + 1001))
        of, grams = np.concatenate([of, short]), np.concatenate([grams, extra])
    order = np.lexsort((grams, of))
    of, grams = of[order], grams[order]
    fresh = np.ones(len(of), bool)
    fresh[1:] = (of[1:] != of[:-1]) | (grams[1:] != grams[:-1])
    of, grams = of[fresh], grams[fresh]
    return grams, np.searchsorted(of, np.arange(len(texts) + 1))


def bucket_keys(grams: np.ndarray, bounds: np.ndarray, chosen: np.ndarray, band: int, partner: np.ndarray, percent: int):
    """Bucket keys of the chosen sets in one band; partner: largest size that each can meet there.

    Returns exact keys and their set, deletion keys and their set, and the spare e of the band."""
    m, whole = allocate(band, percent)
    sizes = (bounds[chosen + 1] - bounds[chosen]).astype(np.int64)
    h = most_differences(sizes, partner, percent)
    e = band_spare(band, percent)
    none = np.zeros(0, U), np.zeros(0, np.int64)
    value = mixed(grams + U(0x632BE59BD9B4E019))
    if whole:
        near, who = [], []
        for i in np.flatnonzero(h > 0):  # with no difference allowed, equal sets are one class already
            own = value[bounds[chosen[i]] : bounds[chosen[i] + 1]]
            total = own.sum(dtype=U)
            for j in range(h[i] + 1):
                picks = np.array(list(itertools.combinations(range(len(own)), j)), np.int64).reshape(math.comb(len(own), j), j)
                near.append(total - own[picks].sum(1, dtype=U))
                who.append(np.full(len(picks), i))
        if not near:
            return *none, *none, e
        return *none, mixed(np.concatenate(near) ^ mixed(U(band) + np.zeros(1, U))), np.concatenate(who), e
    of = np.repeat(np.arange(len(chosen)), sizes)
    flat = np.arange(len(of)) + (bounds[chosen] - np.concatenate([[0], np.cumsum(sizes)[:-1]]))[of]
    segment = ((grams[flat] >> U(32)) * U(m) >> U(32)).astype(np.int64)  # rises with the hash, so segments are runs
    cell = of * m + segment
    head = np.flatnonzero(np.concatenate([[True], cell[1:] != cell[:-1]]))
    total = np.add.reduceat(value[flat], head)
    weight, at, who = np.diff(np.append(head, len(flat))), segment[head], of[head]
    salt = lambda s: mixed(np.asarray(s, np.int64).astype(U) * U(64) + U(band + 1))
    keep = h + 1 + e
    key = mixed(total ^ salt(at))
    order = np.lexsort((key, -weight, who))
    key, place, who = key[order], at[order], who[order]
    start = np.searchsorted(who, np.arange(len(chosen)))
    kept = np.arange(len(who)) - start[who] < keep[who]
    filled = np.diff(np.append(start, len(who)))
    more_key, more_who = [], []
    for i in np.flatnonzero(filled < keep):  # too few segments have elements: empty ones count too
        free = np.setdiff1d(np.arange(m), place[start[i] : start[i] + filled[i]])
        empty = np.sort(mixed(salt(free)))[: keep[i] - filled[i]]
        more_key.append(empty)
        more_who.append(np.full(len(empty), i))
    return np.concatenate([key[kept], *more_key]), np.concatenate([who[kept], *more_who]), *none, e


SKETCH = "doc bigint, n bigint, f1 bigint, f2 bigint, e_own int, e_next int, own array<bigint>, next array<bigint>, near array<bigint>"


def sketches(docs: DataFrame, words: int, percent: int) -> DataFrame:
    """One row for each row of docs: set size, fingerprint and bucket keys (own band, next band, deletions)."""

    def lists(key, who, n):
        order = np.argsort(who, kind="stable")
        offsets = np.searchsorted(who[order], np.arange(n + 1)).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(offsets), pa.array(key[order].view(np.int64)))

    @lean
    def run(batches):
        for batch in batches:
            ids = batch.column("doc_id").cast(pa.int64())
            for a, b, texts in text_blocks(batch.column("text")):
                grams, bounds = ngram_sets(texts, words)
                n, size = b - a, np.diff(bounds)
                sums = [np.concatenate([[U(0)], np.cumsum(mixed(grams + U(s)), dtype=U)]) for s in (11, 12)]
                f1, f2 = ((s[bounds[1:]] - s[bounds[:-1]]).view(np.int64) for s in sums)
                band = np.frexp(np.maximum(size, 1))[1] - 1
                spares, keys, near = [np.zeros(n, np.int32), np.zeros(n, np.int32)], [[], []], []
                for step in (0, 1):
                    reach = largest_partner(size, percent)
                    ready = (size > 0) & ((step == 0) | (reach >= (2 << band)))
                    for z in np.unique(band[ready]):
                        chosen = np.flatnonzero(ready & (band == z))
                        top = np.minimum(reach[chosen], (2 << (z + step)) - 1)
                        k, w, nk, nw, e = bucket_keys(grams, bounds, chosen, int(z) + step, top, percent)
                        spares[step][chosen] = e
                        keys[step].append((k, chosen[w]))
                        near.append((nk, chosen[nw]))
                columns = []
                for found in (keys[0], keys[1], near):
                    k = np.concatenate([x for x, _ in found]) if found else np.zeros(0, U)
                    w = np.concatenate([x for _, x in found]) if found else np.zeros(0, np.int64)
                    columns.append(lists(k, w, n))
                yield pa.RecordBatch.from_arrays(
                    [ids.slice(a, n), pa.array(size.astype(np.int64)), pa.array(f1), pa.array(f2), pa.array(spares[0]), pa.array(spares[1]), *columns],
                    ["doc", "n", "f1", "f2", "e_own", "e_next", "own", "next", "near"],
                )

    return docs.select("doc_id", "text").mapInArrow(run, SKETCH)


#: Members compared with one copy of a leader's text; sets of a bucket that is compared in blocks; sets and bytes of a block.
FOLLOWERS, HOT, BLOCK, BLOCK_BYTES = 2000, 64, 512, 1 << 20


def with_texts(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """a, salt, b, text: the text of every a (b is null), then those of its partners, in every partition in this order. The
    comparison takes long for few bytes, so partitions are dealt by number; a leader of many pairs is dealt by salt."""
    n = int(pairs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    many = pairs.groupBy("a").agg(F.ceil(F.count("*") / FOLLOWERS).cast("int").alias("salts")).where("salts > 1")
    salted = pairs.join(many, "a", "left").select("a", F.coalesce(F.expr("pmod(xxhash64(b), salts)"), F.lit(0)).cast("int").alias("salt"), "b")
    one, other = texts.withColumnRenamed("doc", "a"), texts.withColumnRenamed("doc", "b")
    leaders = salted.select("a", "salt").distinct().join(one, "a").select("a", "salt", F.lit(None).cast("bigint").alias("b"), "text")
    members = salted.join(other, "b").select("a", "salt", "b", "text")
    return leaders.unionAll(members).repartition(n, "a", "salt").sortWithinPartitions("a", "salt", F.col("b").asc_nulls_first())


def links_in_blocks(members: DataFrame, texts: DataFrame, words: int, percent: int) -> DataFrame:
    """Links among the sets of large buckets, without a row for each pair.

    Sets that large buckets connect form a group; a group is dealt into blocks of about BLOCK sets, and every two blocks
    meet in a task of bounded size that counts all intersections by matrix products and returns the links."""
    stars = members.join(members.groupBy("key").agg(F.min("doc").alias("a")), "key").select("a", F.col("doc").alias("b")).distinct()
    groups = durable(connected_components(stars))
    long = texts.select(F.col("doc").alias("id"), F.octet_length("text").alias("bytes"))
    size = F.greatest(F.count("*") / BLOCK, F.sum("bytes") / BLOCK_BYTES)
    blocks = groups.join(long, "id").groupBy("comp").agg(F.ceil(size).cast("int").alias("blocks"))
    label = members.select(F.col("doc").alias("id"), F.col("comp").alias("label")).distinct()
    dealt = groups.join(label, "id").join(blocks, "comp").withColumn("own", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    dealt = dealt.select(F.col("id").alias("doc"), "label", "comp", "own", other.alias("other"))
    dealt = dealt.select("doc", "label", "comp", "own", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j")).join(texts, "doc")

    def compare(rows):
        docs, own, label = (rows.column(c).to_numpy() for c in ("doc", "own", "label"))
        found = [ngram_sets(part, words) for _, _, part in text_blocks(rows.column("text").combine_chunks())]
        grams, size = np.concatenate([g for g, _ in found]), np.concatenate([np.diff(b) for _, b in found])
        _, column, count = np.unique(grams, return_inverse=True, return_counts=True)
        shared = count > 1
        number = np.cumsum(shared) - 1
        owner = np.repeat(np.arange(len(docs)), size)
        keep = shared[column]
        column, owner = number[column[keep]], owner[keep]
        order = np.argsort(column, kind="stable")
        column, owner = column[order], owner[order]
        common = np.zeros((len(docs), len(docs)), np.float32)
        for start in range(0, int(shared.sum()), 4096):  # a slice of the shared n-grams
            a, b = np.searchsorted(column, (start, start + 4096))
            has = np.zeros((len(docs), 4096), np.float32)
            has[owner[a:b], column[a:b] - start] = 1
            common += has @ has.T
        near = 100 * common >= percent * (size[:, None] + size[None, :] - common)
        near &= (label[:, None] < label[None, :]) & (size[:, None] > 0)
        if rows.column("i")[0].as_py() != rows.column("j")[0].as_py():
            near &= own[:, None] != own[None, :]
        # A forest over the components is enough: links inside what is joined already add nothing.
        up: dict = {}

        def top(v):
            while up.setdefault(v, v) != v:
                up[v] = v = up[up[v]]
            return v

        a, b = [], []
        for x, y in zip(*np.nonzero(near), strict=True):
            p, q = top(label[x]), top(label[y])
            if p != q:
                up[p] = q
                a.append(min(docs[x], docs[y]))
                b.append(max(docs[x], docs[y]))
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return dealt.groupBy("comp", "i", "j").applyInArrow(compare, "a bigint, b bigint")


def verified(ordered: DataFrame, words: int, percent: int) -> DataFrame:
    """The rows of with_texts -> the pairs (a, b) whose sets reach the similarity; a leader's set is held for its partners."""

    @lean
    def run(batches):
        leader, sets = None, []
        for batch in batches:
            a, salt = batch.column("a").to_numpy(), batch.column("salt").to_numpy()
            b = batch.column("b").to_pylist()
            keep = []
            for first, _, part in text_blocks(batch.column("text")):
                grams, bounds = ngram_sets(part, words)
                for i, y in enumerate(np.split(grams, bounds[1:-1]), first):
                    if (a[i], salt[i]) != leader:
                        leader, sets = (a[i], salt[i]), []
                    if b[i] is None:
                        sets.append(y)  # one, unless rows share the doc_id
                        keep.append(False)
                        continue
                    common = [len(np.intersect1d(x, y, assume_unique=True)) for x in sets]
                    keep.append(any(100 * c >= percent * (len(x) + len(y) - c) for x, c in zip(sets, common, strict=True)))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return ordered.mapInArrow(run, "a bigint, b bigint")


def candidates(sketch: DataFrame) -> DataFrame:
    """Buckets (key, doc, n) of the sets that can have a partner, without each set's most frequent ones."""
    parts = [
        sketch.select(F.explode(column).alias("key"), "doc", "n", F.lit(part).cast("tinyint").alias("part"), F.col(e).alias("e"))
        for part, column, e in ((0, "own", "e_own"), (1, "next", "e_next"))
    ] + [sketch.select(F.explode("near").alias("key"), "doc", "n", F.lit(2).cast("tinyint").alias("part"), F.lit(0).alias("e")).distinct()]
    rows = parts[0].unionAll(parts[1]).unionAll(parts[2])
    shared = rows.groupBy("key").agg(F.count("*").alias("f")).where("f > 1")
    rows = rows.join(shared, "key")
    by_set = Window.partitionBy("doc", "n", "part")
    ranked = rows.withColumns({"r": F.row_number().over(by_set.orderBy(F.desc("f"), "key")), "all": F.count("*").over(by_set)})
    return ranked.where("part = 2 or (all > e and r > e)").select("key", "doc", "n").distinct()


def linked(buckets: DataFrame, texts: DataFrame, words: int, percent: int, leader_rounds: int = 2) -> DataFrame:
    """(id, comp) of the classes that links join. buckets: key, doc, n; texts: doc, text."""
    spark = buckets.sparkSession
    edges, labels = None, None
    tried = None
    for turn in range(leader_rounds + 1):
        members = buckets
        if labels is not None:
            members = members.join(labels.withColumnRenamed("id", "doc"), "doc", "left").withColumn("comp", F.coalesce("comp", "doc"))
        else:
            members = members.withColumn("comp", F.col("doc"))
        fit = f"least(x.n, y.n) * 100 >= {percent} * greatest(x.n, y.n) and x.comp <> y.comp"
        mixed_key = buckets.groupBy("key").agg(F.count("*").alias("size")).where("size > 1").select("key")
        if turn > 0:
            mixed_key = members.groupBy("key").agg(F.min("comp").alias("least"), F.max("comp").alias("most")).where("least <> most").select("key")
        members = durable(members.join(mixed_key, "key"))
        if members.isEmpty():
            break
        if turn < leader_rounds:
            order = F.struct((F.col("doc") if turn == 0 else F.xxhash64("doc", F.lit(turn))).alias("first"), "doc", "n", "comp")
            leaders = members.groupBy("key").agg(F.min(order).alias("l")).select("key", "l.doc", "l.n", "l.comp")
            pairs = members.alias("x").join(leaders.alias("y"), "key").where(fit)
            pairs = pairs.selectExpr("least(x.doc, y.doc) a", "greatest(x.doc, y.doc) b", "y.doc lead").groupBy("a", "b").agg(F.min("lead").alias("lead"))
        else:
            hot = durable(members.groupBy("key").agg(F.count("*").alias("size")).where(F.col("size") > HOT).select("key"))
            in_hot = members.join(hot, "key")
            cold = members.join(hot, "key", "left_anti")
            pairs = cold.alias("x").join(cold.alias("y"), "key").where(f"x.doc < y.doc and {fit}").selectExpr("x.doc a", "y.doc b", "x.doc lead").distinct()
        if tried is not None:
            pairs = pairs.join(tried, ["a", "b"], "left_anti")
        pairs = durable(pairs)
        tried = pairs if tried is None else tried.unionAll(pairs)
        led = pairs.selectExpr("lead a", "if(lead = a, b, a) b")
        found = durable(verified(with_texts(led, texts), words, percent))
        if turn == leader_rounds and not hot.isEmpty():
            found = found.unionAll(durable(links_in_blocks(in_hot, texts, words, percent)))
        drop(members)
        edges = found if edges is None else edges.unionAll(found)
        labels = durable(connected_components(edges))
    return labels if labels is not None else spark.createDataFrame([], "id bigint, comp bigint")


def components(docs: DataFrame, words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """docs: doc_id, text. Per row: doc_id, n_shingles, component_id."""
    sketch = durable(sketches(docs, words, percent))
    whole = sketch.where("doc is not null and n > 0")
    named_sets = durable(whole.select("doc", "n", "f1", "f2").distinct())
    classes = named_sets.groupBy("n", "f1", "f2").agg(F.min("doc").alias("rep"), F.count("*").alias("copies")).where("copies > 1")
    # Sets of their own need no partner here; nothing follows the join that would keep Spark from splitting a hot class.
    members = durable(named_sets.join(classes, ["n", "f1", "f2"], "left").select("doc", "n", F.coalesce("rep", "doc").alias("rep"), "f1", "f2"))
    copies = members.where("doc <> rep").select("doc", "n", "f1", "f2")
    mark = F.xxhash64("doc", "n", "f1", "f2").alias("mark")
    bitmap = bitmap_of(copies.select(mark), "mark")
    marked = whole.withColumn("mark", F.xxhash64("doc", "n", "f1", "f2"))
    maybe = keep_marked(marked, "mark", bitmap).join(copies, ["doc", "n", "f1", "f2"], "left_anti")
    singles = durable(keep_marked(marked, "mark", bitmap, wanted=False).unionByName(maybe.select(marked.columns)))
    buckets = durable(candidates(singles))

    ids = buckets.select("doc").distinct()
    seen = bitmap_of(ids.select(F.xxhash64("doc").alias("mark")), "mark")
    texts = docs.where("doc_id is not null and text is not null").select(F.col("doc_id").cast("bigint").alias("doc"), "text", F.xxhash64(F.col("doc_id").cast("bigint")).alias("mark"))
    texts = durable(keep_marked(texts, "mark", seen).join(ids, "doc", "left_semi").select("doc", "text"))
    labels = linked(buckets, texts, words, percent)

    reps = durable(members.groupBy("doc").agg(F.min("rep").alias("rep"), F.max("rep").alias("last")))
    bridges = reps.where("rep <> last").select(F.col("rep").alias("a"), F.col("last").alias("b"))
    if not bridges.isEmpty():  # rows of one doc_id with different sets join their classes, too
        labels = connected_components(labels.select(F.col("id").alias("a"), F.col("comp").alias("b")).unionAll(bridges))
    named = reps.join(labels, reps.rep == labels.id, "left").select("doc", F.coalesce("comp", "rep").alias("component_id"))
    out = sketch.select("doc", "n").join(named, "doc", "left")
    return out.select(F.col("doc").alias("doc_id"), F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc").alias("component_id"))


def keep_one(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """One row of docs for each component: that of its least doc_id. Rows without doc_id stay."""
    found = durable(components(docs, words, percent).where("doc_id is not null"))
    gone = durable(found.where("doc_id <> component_id").select("doc_id").distinct())
    again = found.groupBy("doc_id").count().where("count > 1").select("doc_id")
    bitmap = bitmap_of(gone.unionAll(again).select(F.xxhash64("doc_id").alias("mark")), "mark")
    own = unused_name(docs, "mark")
    marked = docs.withColumn(own, F.xxhash64(F.col("doc_id").cast("bigint")))
    maybe = keep_marked(marked, own, bitmap).join(gone, "doc_id", "left_anti").select(marked.columns)
    maybe = maybe.where("doc_id is null").unionByName(maybe.where("doc_id is not null").dropDuplicates(["doc_id"]))
    return keep_marked(marked, own, bitmap, wanted=False).unionByName(maybe).drop(own)
