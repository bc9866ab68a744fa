"""Removal of passages that the corpus has seen before, by suffix automata.

An automaton over reference text tells, word by word, how long a run ending there occurs in
the reference already. Automata of all the corpus cannot be broadcast, as they grow with it, and
pairing every document with every one would be quadratic (figures in README); so the reference is sharded by content.
Every window of ``length`` words is represented by its smallest k-gram of words; equal windows
have equal representatives at equal places. Only representatives that occur again matter.
The stretches of text they stand for come together under them, each distinct stretch once, in the
order of first occurrence, and an automaton per representative is grown through them: the
length of its suffix link at each word is the matching statistic against all that came earlier.

``match_reference`` is the broadcast form for a reference of checked size.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .blocks import trimmed
from .shingles import WordHasher, grams
from .storage import discard, materialise, release

LENGTH = 20
GRAM = 6
#: A representative with more occurrences is divided among its single windows.
FREQUENT = 2_000
#: Words of reference text that may be broadcast: automata take some 400 bytes a word in each worker.
REFERENCE_WORDS = 500_000


class SuffixAutomaton:
    """Suffix automaton over words, grown to the right."""

    def __init__(self) -> None:
        self.next: list[dict] = [{}]
        self.link, self.length, self.last = [-1], [0], 0

    def add(self, word: object) -> int:
        """Appends a word; the length of the longest run ending here that ended earlier too."""
        nxt, link, length = self.next, self.link, self.length
        cur, p = len(nxt), self.last
        nxt.append({})
        length.append(length[p] + 1)
        link.append(0)
        while p >= 0 and word not in nxt[p]:
            nxt[p][word] = cur
            p = link[p]
        if p >= 0:
            q = nxt[p][word]
            if length[p] + 1 == length[q]:
                link[cur] = q
            else:
                copy = len(nxt)
                nxt.append(dict(nxt[q]))
                length.append(length[p] + 1)
                link.append(link[q])
                while p >= 0 and nxt[p].get(word) == q:
                    nxt[p][word] = copy
                    p = link[p]
                link[q] = link[cur] = copy
        self.last = cur
        return length[link[cur]]

    def end_text(self) -> None:
        """What comes next is another text: no run goes across."""
        self.add(object())

    def statistics(self, words: list) -> Iterator[int]:
        """For each word the length of the longest run ending there that the automaton has."""
        state = n = 0
        for word in words:
            while state and word not in self.next[state]:
                state = self.link[state]
                n = self.length[state]
            if word in self.next[state]:
                state, n = self.next[state][word], n + 1
            else:
                state = n = 0
            yield n


def covered(starts: np.ndarray, stops: np.ndarray, n: int) -> np.ndarray:
    """Mask of n words that lie in one of the spans."""
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, stops, -1)
    return np.cumsum(edge[:-1]) > 0


def representatives(h: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(k-gram's number, its place, first and last window it stands for), by place."""
    g = grams(h, gram)
    width = length - gram + 1
    if len(h) < length:
        none = np.zeros(0, np.int64)
        return none, none, none, none
    at = np.lib.stride_tricks.sliding_window_view(g, width).argmin(axis=1) + np.arange(len(g) - width + 1)
    first = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
    last = np.r_[first[1:], len(at)] - 1
    return g[at[first]].view(np.int64), at[first], first, last


def _anchors(batches: Iterator[pa.RecordBatch], length: int, gram: int) -> Iterator[pa.RecordBatch]:
    hasher = WordHasher()
    for batch in batches:
        texts = batch.column("text").to_pylist()
        for a in range(0, len(texts), 2_000):
            found = [representatives(hasher.numbers((text or "").encode().split()), length, gram) for text in texts[a : a + 2_000]]
            offsets = pa.array(np.r_[0, np.cumsum([len(x[0]) for x in found])].astype(np.int32))
            y, _, first, last = (np.concatenate(x) for x in zip(*found, strict=True))
            at = pa.StructArray.from_arrays([pa.array(y), pa.array(first.astype(np.int32)), pa.array((last - first).astype(np.int32))], names=["y", "first", "more"])
            yield pa.RecordBatch.from_arrays([batch.column("id").slice(a, 2_000), batch.column("twin").slice(a, 2_000), pa.ListArray.from_arrays(offsets, at)], names=["id", "twin", "at"])


def _signed(x: int) -> int:
    return x - (1 << 64) * (x >> 63)


def _stretches(batches: Iterator[pa.RecordBatch], length: int) -> Iterator[pa.RecordBatch]:
    """(id, twin, text, at) -> the distinct stretches of each document with the windows they start at."""
    types = {"y": pa.int64(), "d": pa.int64(), "id": pa.int64(), "twin": pa.int64(), "starts": pa.list_(pa.int32()), "windows": pa.int32(), "words": pa.binary()}
    digest = xxhash.xxh3_64_intdigest
    for whole in batches:
        for row in range(0, whole.num_rows, 500):
            batch = whole.slice(row, 500)
            lists = batch.column("at")
            flat, edge = lists.flatten(), np.r_[0, np.cumsum(lists.value_lengths().to_numpy())].tolist()
            ys, firsts, mores, oftens = (flat.field(c).to_pylist() for c in ("y", "first", "more", "often"))
            out: list[tuple] = []
            for i, twin, text, a, b in zip(*(batch.column(c).to_pylist() for c in ("id", "twin", "text")), edge[:-1], edge[1:], strict=True):
                words = text.encode().split()
                own: dict[tuple[int, bytes], list[int]] = {}
                for y, first, more, often in zip(ys[a:b], firsts[a:b], mores[a:b], oftens[a:b], strict=True):
                    if often:
                        for s in range(first, first + more + 1):
                            w = b" ".join(words[s : s + length])
                            own.setdefault((_signed(digest(w, y & 0xFFFFFFFF)), w), []).append(s)
                    else:
                        own.setdefault((y, b" ".join(words[first : first + more + length])), []).append(first)
                for (y, w), starts in own.items():
                    if len(starts) > 1:
                        starts.sort()
                    out.append((y, _signed(digest(w, 1)), i, twin, starts, w.count(b" ") + 2 - length, w))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types.values(), strict=True)], names=list(types))


def _combine(batches: Iterator[pa.RecordBatch], limit: int = 20_000) -> Iterator[pa.RecordBatch]:
    """Equal stretches of a partition become one row: first occurrence and number. What a
    very common passage sends on is bounded by the number of partitions, not of documents."""
    held: dict[tuple[int, int], list] = {}

    def flush() -> pa.RecordBatch:
        rows = [(*k, *v) for k, v in held.items()]
        held.clear()
        types = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=["y", "d", "id", "twin", "start", "m", "words"])

    for batch in batches:
        for y, d, i, twin, starts, words in zip(*(batch.column(c).to_pylist() for c in ("y", "d", "id", "twin", "starts", "words")), strict=True):
            if (own := held.get((y, d))) is None:
                held[y, d] = [i, twin, starts[0], len(starts), words]
            else:
                own[3] += len(starts)
                if (i, twin) < (own[0], own[1]):
                    own[0], own[1], own[2] = i, twin, starts[0]
        if len(held) > limit:
            yield flush()
    if held:
        yield flush()


def earlier_windows(stretches: list[list[bytes]], length: int) -> list[list[int]]:
    """For each stretch, in order, the windows (by start) that an earlier one holds too."""
    automaton, out = SuffixAutomaton(), []
    for words in stretches:
        out.append([e + 1 - length for e, w in enumerate(words) if automaton.add(w) >= length])
        automaton.end_text()
    return out


def _grow(batches: Iterator[pa.RecordBatch], length: int) -> Iterator[pa.RecordBatch]:
    """Stretches sorted by representative -> first occurrence and repeated windows of each
    distinct one that occurs again or holds some."""
    types = {"y": pa.int64(), "d": pa.int64(), "id": pa.int64(), "twin": pa.int64(), "start": pa.int32(), "repeated": pa.list_(pa.int32())}
    out: list[tuple] = []

    def settle(y: int, firsts: dict[int, list]) -> None:
        if len(firsts) == 1:
            ((d, (i, twin, start, m, _)),) = firsts.items()
            if m > 1:
                out.append((y, d, i, twin, start, ()))
            return
        ranked = sorted(firsts.items(), key=lambda x: x[1][:3])
        windows = earlier_windows([x[4].split(b" ") for _, x in ranked], length)
        out.extend((y, d, i, twin, start, w) for (d, (i, twin, start, m, _)), w in zip(ranked, windows, strict=True) if m > 1 or w)

    def table() -> pa.RecordBatch:
        made = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types.values(), strict=True)], names=list(types))
        out.clear()
        return made

    current, firsts = None, {}
    for batch in batches:
        for y, d, i, twin, start, m, words in zip(*(batch.column(c).to_pylist() for c in ("y", "d", "id", "twin", "start", "m", "words")), strict=True):
            if y != current:
                if firsts:
                    settle(current, firsts)
                current, firsts = y, {}
            if (own := firsts.get(d)) is None:
                firsts[d] = [i, twin, start, m, words]
            else:
                own[3] += m
                if (i, twin, start) < (own[0], own[1], own[2]):
                    own[0], own[1], own[2] = i, twin, start
        if len(out) > 10_000:
            yield table()
    if firsts:
        settle(current, firsts)
    if out:
        yield table()


def _spans(batches: Iterator[pa.RecordBatch], length: int) -> Iterator[pa.RecordBatch]:
    """Occurrences with their stretch's finding -> repeated spans of words [start, stop) by document."""
    for batch in batches:
        ids, twins, a, b = [], [], [], []
        for i, twin, starts, n, f_id, f_twin, f_start, repeated in zip(*(batch.column(c).to_pylist() for c in ("id", "twin", "starts", "windows", "f_id", "f_twin", "f_start", "repeated")), strict=True):
            for s in starts:
                if i == f_id and twin == f_twin and s == f_start:
                    for w in repeated:
                        if a and b[-1] == s + w + length - 1 and ids[-1] == i and twins[-1] == twin:
                            b[-1] += 1
                        else:
                            ids.append(i)
                            twins.append(twin)
                            a.append(s + w)
                            b.append(s + w + length)
                else:
                    ids.append(i)
                    twins.append(twin)
                    a.append(s)
                    b.append(s + n + length - 1)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(twins, pa.int64()), pa.array(a, pa.int32()), pa.array(b, pa.int32())], names=["id", "twin", "start", "stop"])


def twin_of(docs: DataFrame, id_col: str, text_col: str) -> Column:
    """Tells different texts under one id apart: 0 throughout if no id has two, else a hash of the text."""
    h = F.xxhash64(F.col(f"`{text_col}`"))
    keyed = docs.where(F.col(f"`{text_col}`").isNotNull()).select(F.col(f"`{id_col}`").cast("bigint").alias("id"), h.alias("h")).where("id is not null")
    several = keyed.groupBy("id").agg(F.min("h").alias("a"), F.max("h").alias("b")).where("a <> b")
    return h if several.head(1) else F.lit(0).cast("bigint")


def repeated_spans(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, id_col: str = "doc_id", text_col: str = "text", frequent: int = FREQUENT, twin: Column | None = None) -> DataFrame:
    """(id, twin, spans array<struct<start, stop>>): words covered by windows that also start earlier.

    Earlier: in a document of smaller id, or in the same one further to the front. Documents
    without such windows have no row. ids are integers. Different texts under one id are documents of
    their own, told apart and ordered by twin; equal rows are one document.
    """
    spark = docs.sparkSession
    twin = twin_of(docs, id_col, text_col) if twin is None else twin
    rows = docs.where(F.col(text_col).isNotNull() & F.col(id_col).isNotNull()).select(F.col(id_col).cast("bigint").alias("id"), twin.alias("twin"), F.col(text_col).alias("text"))
    listed = materialise(rows.mapInArrow(lambda b: trimmed(_anchors(b, length, gram)), "id bigint, twin bigint, at array<struct<y:bigint,first:int,more:int>>"), "representatives")
    anchors = listed.select("id", "twin", F.explode("at").alias("at")).select("id", "twin", "at.*")
    # these tables grow with the corpus: merge joins, never a broadcast
    # both sides and the result are written, so that nothing but the join needs a representative's
    # rows together and a very common one can be split over tasks
    again = materialise(anchors.groupBy("y").agg(F.count("*").alias("m")).where("m > 1"), "again")
    release(spark)
    found = anchors.join(again.hint("merge"), "y").select("id", "twin", F.struct("y", "first", "more", (F.col("m") > frequent).alias("often")).alias("at"))
    found = materialise(found, "found")
    discard(listed)
    release(spark)
    kept = materialise(found.groupBy("id", "twin").agg(F.collect_list("at").alias("at")), "anchors")
    discard(again)
    discard(found)
    release(spark)

    schema = "y bigint, d bigint, id bigint, twin bigint, starts array<int>, windows int, words binary"
    seen = materialise(rows.join(kept.hint("merge"), ["id", "twin"]).select("id", "twin", "text", "at").mapInArrow(lambda b: trimmed(_stretches(b, length)), schema), "stretches")
    release(spark)

    combined = seen.select("y", "d", "id", "twin", "starts", "words").mapInArrow(lambda b: trimmed(_combine(b)), "y bigint, d bigint, id bigint, twin bigint, start int, m bigint, words binary")
    grown = combined.repartition("y").sortWithinPartitions("y").mapInArrow(lambda b: trimmed(_grow(b, length)), "y bigint, d bigint, id bigint, twin bigint, start int, repeated array<int>")
    grown = materialise(grown, "grown")
    release(spark)

    told = seen.select("y", "d", "id", "twin", "starts", "windows").join(grown.select("y", "d", F.col("id").alias("f_id"), F.col("twin").alias("f_twin"), F.col("start").alias("f_start"), "repeated").hint("merge"), ["y", "d"])
    spans = told.mapInArrow(lambda b: trimmed(_spans(b, length)), "id bigint, twin bigint, start int, stop int")
    return spans.groupBy("id", "twin").agg(F.collect_list(F.struct("start", "stop")).alias("spans"))


def _removed(batches: Iterator[pa.RecordBatch], text_col: str, with_text: bool, made: list[str]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        n, gone, sha, kept = [], [], [], []
        lists = batch.column("spans")
        flat, edge = lists.flatten(), np.r_[0, np.cumsum(np.nan_to_num(lists.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64))].tolist()
        start, stop = flat.field("start").to_numpy(), flat.field("stop").to_numpy()
        for text, a, b in zip(batch.column(text_col).to_pylist(), edge[:-1], edge[1:], strict=True):
            words = (text or "").encode().split()
            n.append(len(words))
            if a < b:
                mask = covered(start[a:b], stop[a:b], len(words))
                words = [w for w, m in zip(words, mask.tolist(), strict=True) if not m]
            gone.append(n[-1] - len(words))
            joined = b" ".join(words)
            sha.append(hashlib.sha256(joined).hexdigest())
            if with_text:
                kept.append(text if text is None or not gone[-1] else joined.decode())
        names = [c for c in batch.schema.names if c not in ("spans", "twin") and (with_text or c != text_col)]
        columns = [pa.array(kept, pa.string()) if c == text_col else batch.column(c) for c in names]
        yield pa.RecordBatch.from_arrays([*columns, pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(sha, pa.string())], names=[*names, *made])


def remove_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """One row per row of docs: id, n_words, n_removed, kept_sha256; with_text: all columns as well.

    Words are the runs between ASCII white space. A word goes if a window of ``length`` words
    that covers it starts earlier as well (smaller id, or earlier in the same document). Null
    texts have no words and stay null; texts of which nothing goes stay as they are, of others
    the kept words are joined by one space. Rows without an id stay as they are. Different texts under one
    id are documents of their own (the one with the smaller hash comes first); equal rows are one document
    and get equal results. An empty table gives no rows. Columns named like those made here, ``spans`` or
    ``twin`` are replaced or dropped.
    """
    if not 0 < gram <= length:
        raise ValueError("gram must lie between 1 and length")
    twin = twin_of(docs, id_col, text_col)
    spans = materialise(repeated_spans(docs, length, gram, id_col, text_col, twin=twin), "spans")
    release(docs.sparkSession)
    made = ["n_words", "n_removed", "kept_sha256"]
    kept = [f for f in docs.schema.fields if f.name not in (*made, "spans", "twin") and (with_text or f.name in (id_col, text_col))]
    rows = docs.select(*(F.col(f"`{f.name}`") for f in kept), twin.alias("twin"))
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept if with_text or f.name != text_col), "n_words bigint, n_removed bigint, kept_sha256 string"])
    found = spans.select(F.col("id").alias("span_id"), F.col("twin").alias("span_twin"), "spans").hint("merge")
    joined = rows.join(found, (F.col(f"`{id_col}`").cast("bigint") == F.col("span_id")) & (F.col("twin") == F.col("span_twin")), "left").drop("span_id", "span_twin", "twin")
    return joined.mapInArrow(lambda b: trimmed(_removed(b, text_col, with_text, made)), schema)


def reference_texts(reference: DataFrame, text_col: str = "text") -> list[str]:
    """The texts of a reference table whose words are counted before they are collected."""
    n = reference.agg(F.sum(F.size(F.split(F.trim(F.col(text_col)), r"[\x20\x09-\x0D]+")))).first()[0] or 0
    if n > REFERENCE_WORDS:
        raise ValueError(f"the reference has over {REFERENCE_WORDS} words; use repeated_spans on the union")
    return [r[0] for r in reference.where(F.col(text_col).isNotNull()).select(text_col).collect()]


def match_reference(docs: DataFrame, reference: list[str], length: int = LENGTH, id_col: str = "doc_id", text_col: str = "text", shard_words: int = 100_000) -> DataFrame:
    """One row per row of docs: id, spans, n_words, n_removed, kept_sha256.

    spans are the maximal runs of at least ``length`` words that a reference text holds, which go; the others are
    joined by one space. Null texts have no words; an empty table gives no rows. The reference is divided into
    shards of at most shard_words (a longer text is a shard of its own); the shards are broadcast, each worker
    grows their automata, and the documents stream through for matching statistics. More than REFERENCE_WORDS raise an error.
    """
    words = [(x or "").encode().split() for x in reference]
    if sum(map(len, words)) > REFERENCE_WORDS:
        raise ValueError(f"the reference has over {REFERENCE_WORDS} words; use repeated_spans on the union")
    shards: list[list[list[bytes]]] = [[]]
    for w in words:
        if shards[-1] and sum(map(len, shards[-1])) + len(w) > shard_words:
            shards.append([])
        shards[-1].append(w)
    shared = docs.sparkSession.sparkContext.broadcast(shards)
    span_type = pa.list_(pa.struct([("start", pa.int32()), ("stop", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automata = []
        for shard in shared.value:
            automata.append(SuffixAutomaton())
            for text in shard:
                for w in text:
                    automata[-1].add(w)
                automata[-1].end_text()
        for batch in batches:
            out, n, gone, sha = [], [], [], []
            for text in batch.column("text").to_pylist():
                own = (text or "").encode().split()
                hits = [(e + 1 - m, e + 1) for a in automata for e, m in enumerate(a.statistics(own)) if m >= length]
                mask = covered(np.array([h[0] for h in hits], np.int64), np.array([h[1] for h in hits], np.int64), len(own)) if own else np.zeros(0, bool)
                edge = np.flatnonzero(np.diff(np.r_[0, mask.astype(np.int8), 0]))
                out.append([{"start": int(a), "stop": int(b)} for a, b in zip(edge[::2], edge[1::2], strict=True)])
                n.append(len(own))
                gone.append(int(mask.sum()))
                sha.append(hashlib.sha256(b" ".join(w for w, m in zip(own, mask.tolist(), strict=True) if not m)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(out, span_type), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(sha, pa.string())], names=["id", "spans", "n_words", "n_removed", "kept_sha256"])

    id_type = docs.schema[id_col].dataType.simpleString()
    schema = f"id {id_type}, spans array<struct<start:int,stop:int>>, n_words bigint, n_removed bigint, kept_sha256 string"
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(lambda b: trimmed(run(b)), schema).withColumnRenamed("id", id_col)
