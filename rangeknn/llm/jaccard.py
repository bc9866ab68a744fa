"""Exact Jaccard join of documents on word shingles as a blocked sparse matrix product.

The incidence matrix (documents by shingles) is never multiplied as a whole. Equal rows are
one class. Size bounds leave out what cannot link: of a set of n shingles a partner lacks at
most n - ceil(t n), so a set with more shingles of its own than that has no partner, and
any partner shares one of the first n - ceil(t n) + 1 shingles in an order that all sets
have in common, rarest first. Sets that meet there form clusters; each cluster, if large in blocks
of bounded size of which only those with a shingle in common meet, is multiplied with overlap counts
accumulated shingle by shingle. All links are found; they leave a task as one number for each set, not as pairs.

Own and rare shingles are told by counting those of the lowest part of the hash range over
all documents, which is enough to order the prefixes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .blocks import Forest, runs, trimmed
from .graph import components
from .shingles import WordHasher, grams
from .storage import materialise, release

K = 5
PERCENT = 80
#: Share of the hash range whose shingles are counted: the prefixes take a fifth, and some more.
COUNTED = 0.25
#: Bounds of a block: its shingles, and its sets, so that the overlaps of two blocks are held at once.
BLOCK_SHINGLES = 1_000_000
BLOCK_SETS = 700
#: Overlaps of a block of rows, and steps of their sum, that a task holds at once.
CELLS = 2_000_000


def shingle_set(hasher: WordHasher, text: str | None, k: int) -> np.ndarray:
    """Distinct shingles as sorted 63-bit numbers; the words of a shorter text are one."""
    h = hasher.numbers((text or "").encode().lower().split())
    return np.unique(grams(h, min(k, len(h))) >> np.uint64(1)).view(np.int64) if len(h) else np.zeros(0, np.int64)


def prefix_size(n: int, percent: int) -> int:
    return n - -(-percent * n // 100) + 1


def digest(blob: bytes) -> tuple[int, int]:
    d = xxhash.xxh3_128_digest(blob)
    return int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True)


def _signatures(batches: Iterator[pa.RecordBatch], k: int, cut: int, percent: int) -> Iterator[pa.RecordBatch]:
    """(id, text) -> size and digest of the set, its shingles below the cut, and more of them if
    the prefix needs them."""
    hasher = WordHasher()
    for batch in batches:
        texts = batch.column("text").to_pylist()
        for at in range(0, len(texts), 1_000):
            n, low, d1, d2, parts = [], [], [], [], []
            for text in texts[at : at + 1_000]:
                s = shingle_set(hasher, text, k)
                one, two = digest(s.tobytes())
                n.append(len(s))
                low.append(int(np.searchsorted(s, cut)))
                d1.append(one)
                d2.append(two)
                parts.append(s[: max(low[-1], min(len(s), prefix_size(len(s), percent)))])
            offsets = pa.array(np.r_[0, np.cumsum([len(x) for x in parts])].astype(np.int32))
            lists = pa.ListArray.from_arrays(offsets, pa.array(np.concatenate(parts)))
            yield pa.RecordBatch.from_arrays([batch.column("id").slice(at, 1_000), *(pa.array(x, pa.int64()) for x in (n, low, d1, d2)), lists], names=["id", "n", "low", "d1", "d2", "x"])


def _sets(batches: Iterator[pa.RecordBatch], k: int) -> Iterator[pa.RecordBatch]:
    """Sets of the rows of classes' ids; a row that is not the class's own text (repeated id) weighs nothing."""
    hasher = WordHasher()
    for batch in batches:
        texts = batch.column("text").to_pylist()
        for at in range(0, len(texts), 1_000):
            part = batch.slice(at, 1_000)
            sets = [shingle_set(hasher, t, k).tobytes() for t in texts[at : at + 1_000]]
            own = zip(sets, *(part.column(c).to_pylist() for c in ("d1", "d2", "m")), strict=True)
            weight = [m if digest(s) == (d1, d2) else 0 for s, d1, d2, m in own]
            yield pa.RecordBatch.from_arrays([*(part.column(c) for c in ("id", "block", "tasks", "d1", "d2")), pa.array(weight, pa.int64()), pa.array(sets, pa.binary())], names=["id", "block", "tasks", "d1", "d2", "weight", "shingles"])


def overlaps(sets: list[np.ndarray], split: int = 0) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """(first, last, a, b, shared shingles) for blocks of rows first..last-1: a, counted from first,
    and b cover all pairs of sets with a shingle in common, both ways; with split, a is below it and b is not.

    Columns of many rows are multiplied as a dense matrix, the others go by their postings.
    """
    n, top = len(sets), split or len(sets)
    wide_by = n - split
    size = np.array([len(s) for s in sets], np.int64)
    _, column, often = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(n), size)
    wide = (often > 1) & (8 * often > n)
    name = np.cumsum(wide) - 1
    dense = np.zeros((n, int(wide.sum())), bool)
    keep = wide[column]
    dense[row[keep], name[column[keep]]] = True
    keep = ~keep & (often[column] > 1)
    row, column = row[keep], column[keep]
    right = row >= split
    docs = row[right][np.argsort(column[right], kind="stable")] - split
    at = np.r_[0, np.cumsum(np.bincount(column[right], minlength=len(often)))]
    row, column = row[row < top], column[row < top]
    width = at[column + 1] - at[column]
    steps = np.r_[0, np.cumsum(width)]
    height, slab = max(1, CELLS // wide_by), max(128, CELLS // n)
    for first in range(0, top, height):
        last = min(top, first + height)
        e, end = np.searchsorted(row, [first, last]).tolist()
        sparse = not dense.shape[1] and steps[end] - steps[e] < (last - first) * wide_by // 8
        over = None if sparse else np.zeros((last - first, wide_by), np.float32)
        for c in range(0, dense.shape[1], slab):
            part = dense[:, c : c + slab].astype(np.float32)
            over += part[first:last] @ part[split:].T
        pairs, count = np.zeros(0, np.int64), np.zeros(0, np.int64)
        while e < end:
            to = end if sparse else min(end, max(e + 1, int(np.searchsorted(steps, steps[e] + CELLS, "right")) - 1))
            w = width[e:to]
            take = np.repeat(at[column[e:to]] - (steps[e:to] - steps[e]), w) + np.arange(steps[to] - steps[e])
            key = np.repeat(row[e:to] - first, w) * wide_by + docs[take]
            if sparse:
                pairs, count = np.unique(key, return_counts=True)
            else:
                over += np.bincount(key, minlength=over.size).reshape(over.shape)
            e = to
        if not sparse:
            pairs = np.flatnonzero(over)
            count = over.ravel()[pairs].astype(np.int64)
        a, b = pairs // wide_by, pairs % wide_by + split
        other = a + first != b
        yield first, last, a[other], b[other], count[other]


def linked(sets: list[np.ndarray], percent: int, weight: np.ndarray, split: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """For each set the first one (by place) of its component, and the weights of all it links with.

    With split, only links between the sets before that place and the others are looked at.
    """
    n = len(sets)
    size = np.array([len(s) for s in sets], np.int64)
    root, links, forest, tried = np.arange(n), np.zeros(n, np.int64), Forest(n), 0
    if not size.sum():
        return root, links
    for first, last, a, b, shared in overlaps(sets, split):
        hit = (100 + percent) * shared >= percent * (size[first + a] + size[b])
        a, b = a[hit], b[hit]
        links[first:last] += np.bincount(a, weight[b], minlength=last - first).astype(np.int64)
        if split:
            links += np.bincount(b, weight[first + a], minlength=n).astype(np.int64)
        ends = np.searchsorted(a, np.arange(last - first + 1)).tolist()
        for i in range(first, last):
            far = root[b[ends[i - first] : ends[i - first + 1]]]
            far = far[far != root[i]]
            if len(far):
                far = np.unique(far).tolist()
                for j in far:
                    forest.join(i, j)
                tried += len(far)
            if tried > max(16, n // 64):  # what is one component by now needs no second look
                root[:], tried = [forest.root(j) for j in range(n)], 0
    root[:] = [forest.root(j) for j in range(n)]
    return root, links


def _link(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """Of each set with a link: one of its component, and the texts it links with. Links inside a block are those of
    the block's own task; the task of two blocks takes only the links between them."""
    for _, t in runs(batches, "task"):
        ids, block = t["id"].to_numpy(), t["block"].to_numpy()
        order = np.lexsort((ids, block))
        split = 0 if t["inner"][0].as_py() else int(np.searchsorted(block[order], block.min(), "right"))
        if split == len(ids):
            continue
        blobs = t["shingles"].to_pylist()
        ids, d1, d2, weight = (t[c].to_numpy()[order] for c in ("id", "d1", "d2", "weight"))
        if (ids[1:] == ids[:-1]).any():  # one row stands for a class, also under a repeated id
            weight, seen = weight.copy(), set()
            for i in np.flatnonzero(weight).tolist():
                if (d1[i], d2[i]) in seen:
                    weight[i] = 0
                seen.add((d1[i], d2[i]))
        sets = [np.frombuffer(blobs[i], np.int64) for i in order]
        root, links = linked(sets, percent, weight, split)
        links[weight == 0] = 0
        met = np.flatnonzero((root != np.arange(len(ids))) | (links > 0))
        n = np.array([len(sets[i]) for i in met], np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in (ids[met], ids[root[met]], n, d1[met], d2[met], links[met])], names=["a", "b", "n", "d1", "d2", "links"])


def _blocks(clusters: DataFrame, prefix: DataFrame, percent: int, block_sets: int, block_shingles: int) -> DataFrame:
    """(id, block, tasks array<struct<task, inner>>): where the sets of clusters (id, cluster, n) meet.

    A cluster of bounded size is one task. A larger one, which may be no more than a chain of chance meetings,
    is divided into blocks of sets with a prefix shingle in common, and a set goes only to the tasks of blocks
    that hold a set of fitting size with one of its own prefix shingles. So a task's size is bounded, and the
    number of tasks of a set by the blocks of those it shares a rare shingle with, not by its cluster.
    """
    size = (F.count("*").alias("sets"), F.sum("n").alias("shingles"))
    parts = F.greatest(F.ceil(F.col("sets") / block_sets), F.ceil(F.col("shingles") / block_shingles))
    sizes = clusters.groupBy("cluster").agg(*size).select("cluster", parts.alias("parts"))
    dealt = materialise(clusters.join(sizes, "cluster"), "dealt")
    whole = F.array(F.struct(F.xxhash64("cluster").alias("task"), F.lit(True).alias("inner")))
    small = dealt.where("parts = 1").select("id", F.lit(0).cast("bigint").alias("block"), whole.alias("tasks"))
    large = dealt.where("parts > 1").select("id", "cluster", "n")
    if not large.head(1):
        return small

    x = prefix.join(large.hint("merge"), "id")
    own = materialise(x.groupBy("id", "cluster", "n").agg(F.min("x").alias("anchor")), "anchors")
    sizes = own.groupBy("cluster", "anchor").agg(*size).select("cluster", "anchor", "sets", "shingles", parts.alias("parts"))
    sizes = materialise(sizes, "anchor_sizes")
    rest = sizes.where("parts = 1").groupBy("cluster").agg(F.sum("sets").alias("sets"), F.sum("shingles").alias("shingles")).select("cluster", parts.alias("rest"))
    # an anchor with many sets has blocks of its own, the others share some
    frequent = F.xxhash64("cluster", "anchor", F.pmod(F.xxhash64("id"), F.col("parts")))
    shared = F.xxhash64("cluster", F.lit("rest"), F.pmod(F.xxhash64("anchor"), F.col("rest")))
    block = F.when(F.col("parts") > 1, frequent).otherwise(shared)
    placed = own.join(sizes.select("cluster", "anchor", "parts"), ["cluster", "anchor"]).join(rest, "cluster", "left").select("id", "n", block.alias("block"))
    x = materialise(prefix.join(materialise(placed, "placed").hint("merge"), "id"), "block_shingles")
    held = x.groupBy("x", "block").agg(F.min("n").alias("lo"), F.max("n").alias("hi"), F.count("*").alias("m"))
    # written, so that a very common shingle's rows can be split over tasks in the join
    held = materialise(held.groupBy("x").agg(F.collect_list(F.struct("block", "lo", "hi", "m")).alias("held")), "held")
    fits = lambda b: (100 * b["hi"] >= percent * F.col("n")) & (percent * b["lo"] <= 100 * F.col("n")) & ((b["block"] != F.col("block")) | (b["m"] > 1))
    meets = x.join(held.hint("merge"), "x").select("id", "block", F.array_sort(F.transform(F.filter("held", fits), lambda b: b["block"])).alias("meets"))
    meets = meets.groupBy("id", "block").agg(F.array_distinct(F.flatten(F.collect_set("meets"))).alias("meets"))
    pair = lambda j: F.struct(F.xxhash64(F.least(j, F.col("block")), F.greatest(j, F.col("block"))).alias("task"), (j == F.col("block")).alias("inner"))
    return small.unionByName(meets.select("id", "block", F.transform("meets", pair).alias("tasks")))


def jaccard_components(docs: DataFrame, percent: int = PERCENT, k: int = K, id_col: str = "doc_id", text_col: str = "text", block_shingles: int = BLOCK_SHINGLES, block_sets: int = BLOCK_SETS) -> DataFrame:
    """One row per row of docs: id, n_shingles, class_id, component_id, n_links.

    Words are the runs between ASCII white space, A-Z lower-cased; sets link when 100 *
    intersection >= percent * union. A text of fewer than k words is one shingle; null texts and those without
    words have none and link with nothing. class_id is the smallest id with an equal set,
    component_id the smallest id reachable by links, n_links the number of other rows with an id that
    the row links with, equal sets included. ids are integers; rows that share one count as
    one document with several texts, and a null id links with nothing. An empty table gives no
    rows; other columns are ignored.
    """
    if not 50 <= percent <= 100:
        raise ValueError("percent must lie between 50 and 100")
    spark = docs.sparkSession
    counted = max(COUNTED, 1.25 * (100 - percent) / 100)
    cut = int(counted * 2**63) if counted < 1 else 2**63 - 1
    rows = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    # these tables grow with the corpus: merge joins, never a broadcast
    signed = materialise(rows.mapInArrow(lambda b: trimmed(_signatures(b, k, cut, percent)), "id bigint, n bigint, low bigint, d1 bigint, d2 bigint, x array<bigint>"), "signatures")
    classes = materialise(signed.where("n > 0 and id is not null").groupBy("n", "low", "d1", "d2").agg(F.min("id").alias("class_id"), F.count("*").alias("m")), "classes")
    release(spark)

    named = rows.where("id is not null")
    x = signed.where("id is not null").select("id", F.explode("x").alias("x"))
    often = x.groupBy("x").agg(F.count("*").alias("df")).where("df > 1")
    shared = x.join(often.hint("merge"), "x").select("id", "x", "df")
    # a set's shared shingles in the common order: the counted ones by number, then the others
    need = (F.col("n") - F.ceil(F.col("n") * percent / 100) + 1) - (F.col("low") - F.count(F.when(F.col("x") < cut, 1)).over(Window.partitionBy("id")))
    order = Window.partitionBy("id").orderBy((F.col("x") >= cut), F.when(F.col("x") < cut, F.col("df")).otherwise(0), "x")
    prefix = shared.join(classes.select(F.col("class_id").alias("id"), "n", "low").hint("merge"), "id").withColumn("need", need).withColumn("turn", F.row_number().over(order)).where("turn <= need").select("id", "x")
    prefix = materialise(prefix, "prefixes")
    release(spark)

    firsts = prefix.groupBy("x").agg(F.min("id").alias("first"), F.count("*").alias("m")).where("m > 1").select("x", "first")
    meets = prefix.join(firsts, "x").where("id <> first").select(F.col("id").alias("a"), F.col("first").alias("b")).distinct()
    clusters = components(meets).withColumnRenamed("component_id", "cluster")
    clusters = materialise(clusters.join(classes.select(F.col("class_id").alias("id"), "n", "d1", "d2", "m"), "id"), "clusters")
    release(spark)

    tasks = materialise(_blocks(clusters.select("id", "cluster", "n"), prefix, percent, block_sets, block_shingles), "tasks")
    placed = clusters.select("id", "d1", "d2", "m").join(tasks.hint("merge"), "id")
    release(spark)
    kinds = "id bigint, block bigint, tasks array<struct<task:bigint,inner:boolean>>, d1 bigint, d2 bigint, weight bigint, shingles binary"
    sets = named.join(placed.hint("merge"), "id").select("id", "text", "block", "tasks", "d1", "d2", "m").mapInArrow(lambda b: trimmed(_sets(b, k)), kinds)
    work = sets.withColumn("at", F.explode("tasks")).select("id", "block", "at.task", "at.inner", "d1", "d2", "weight", "shingles").repartition("task").sortWithinPartitions("task")
    links = materialise(work.mapInArrow(lambda b: trimmed(_link(b, percent)), "a bigint, b bigint, n bigint, d1 bigint, d2 bigint, links bigint"), "links")
    release(spark)

    found = components(links.where("a <> b"))
    met = links.where("links > 0").groupBy("n", "d1", "d2").agg(F.sum("links").alias("links"))
    per_class = classes.join(found.withColumnRenamed("id", "class_id"), "class_id", "left").join(met, ["n", "d1", "d2"], "left")
    per_class = per_class.select("n", "d1", "d2", "class_id", F.coalesce("component_id", "class_id").alias("component_id"), (F.coalesce("links", F.lit(0)) + F.col("m") - 1).alias("n_links"))
    per_class = materialise(per_class, "per_class")
    out = signed.drop("x").join(per_class.hint("merge"), ["n", "d1", "d2"], "left")
    return out.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("class_id", "id").alias("class_id"), F.coalesce("component_id", "id").alias("component_id"), F.when(F.col("id").isNotNull(), F.coalesce("n_links", F.lit(0))).otherwise(0).cast("bigint").alias("n_links"))
