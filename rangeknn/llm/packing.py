"""Best-fit packing by a grouping genetic algorithm on islands.

Pieces of documents are dealt to shards of bounded size. Each shard is evolved on several islands:
crossover copies well-filled bins of one parent whole into another, removes bins that
repeat their pieces and best-fits what that displaced. Between epochs each island's elite
moves on to the next island. A shard that reaches its lower bound stops. What lies in badly filled
bins at the end is pooled over shards and packed once more.
"""

from __future__ import annotations

import math
import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .batch_bpe import BatchBpe
from .blocks import trimmed
from .segments import SegmentEncoder
from .storage import materialise


@dataclass(frozen=True)
class Evolution:
    shard_items: int = 4_096
    islands: int = 2
    epochs: int = 3
    population: int = 4
    generations: int = 8
    elites: int = 2
    share: float = 0.5
    poor_fill: float = 0.97


def best_fit(lengths: np.ndarray, items: list[int], bins: list[list[int]], room: list[int], capacity: int) -> None:
    """Puts items, longest first, each where least room is left over; opens bins as needed."""
    free = sorted((r, b) for b, r in enumerate(room) if r > 0)
    for i in sorted(items, key=lambda i: (-lengths[i], i)):
        need = int(lengths[i])
        at = bisect_left(free, (need, -1))
        if at < len(free):
            r, b = free.pop(at)
        else:
            r, b = capacity, len(bins)
            bins.append([])
            room.append(capacity)
        bins[b].append(i)
        room[b] = r - need
        if room[b]:
            insort(free, (room[b], b))


class Island:
    """Individuals are arrays item -> bin, bins numbered from 0."""

    def __init__(self, lengths: np.ndarray, capacity: int, how: Evolution, seed: int) -> None:
        self.lengths, self.capacity, self.how = lengths, capacity, how
        self.bound = -(-int(lengths.sum()) // capacity)
        self.rng = np.random.default_rng(seed)

    def assign(self, bins: list[list[int]]) -> np.ndarray:
        out = np.empty(len(self.lengths), np.int32)
        for b, items in enumerate(x for x in bins if x):
            out[items] = b
        return out

    def first(self, shuffled: bool) -> np.ndarray:
        bins: list[list[int]] = []
        room: list[int] = []
        items = list(range(len(self.lengths)))
        if shuffled:  # a random part goes first, in its own order
            some = self.rng.permutation(len(items))[: len(items) // 3].tolist()
            for i in some:
                best_fit(self.lengths, [i], bins, room, self.capacity)
            items = sorted(set(items) - set(some))
        best_fit(self.lengths, items, bins, room, self.capacity)
        return self.assign(bins)

    def fitness(self, x: np.ndarray) -> tuple[int, float]:
        fill = np.bincount(x, self.lengths) / self.capacity
        return len(fill), -float((fill * fill).mean()) if len(fill) else 0.0

    def cross(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        fill = np.bincount(a, self.lengths)
        ranked = np.argsort(-(fill + self.rng.random(len(fill)) * 0.02 * self.capacity))
        chosen = ranked[: max(1, int(len(ranked) * self.how.share))]
        taken = np.isin(a, chosen)
        gone = np.zeros(int(b.max()) + 1, bool)
        gone[b[taken]] = True
        displaced = np.flatnonzero(~taken & gone[b]).tolist()
        stays = np.flatnonzero(~taken & ~gone[b])
        bins: list[list[int]] = []
        for rows, of in ((np.flatnonzero(taken), a), (stays, b)):
            order = rows[np.argsort(of[rows], kind="stable")]
            bins += [x.tolist() for x in np.split(order, np.flatnonzero(np.diff(of[order])) + 1) if len(x)]
        room = [self.capacity - int(self.lengths[x].sum()) for x in bins]
        best_fit(self.lengths, displaced, bins, room, self.capacity)
        return self.assign(bins)

    def evolve(self, population: list[np.ndarray]) -> list[np.ndarray]:
        """The fittest individuals after some generations, best first."""
        if not len(self.lengths):
            return [np.zeros(0, np.int32)]
        population = population or [self.first(False)]
        ranked = sorted(population, key=self.fitness)
        if self.fitness(ranked[0])[0] == self.bound:
            return ranked[:1]
        while len(ranked) < self.how.population:
            ranked.append(self.first(True))
        for _ in range(self.how.generations):
            ranked.sort(key=self.fitness)
            if self.fitness(ranked[0])[0] == self.bound:
                break
            young = []
            for _ in range(len(ranked)):
                i, j = sorted(self.rng.choice(len(ranked), 2, replace=False).tolist())
                young.append(self.cross(ranked[i], ranked[j]))
            ranked = sorted([*ranked, *young], key=self.fitness)[: self.how.population]
        return sorted(ranked, key=self.fitness)


@lru_cache(maxsize=2)
def _encoder(path: str, spaced: bool, limit: int) -> SegmentEncoder:
    return SegmentEncoder(BatchBpe(path).encode_many, spaced, limit)


def _pieces(batches: Iterator[pa.RecordBatch], path: str, spaced: bool, capacity: int, end_id: int, limit: int) -> Iterator[pa.RecordBatch]:
    encoder, end = _encoder(path, spaced, limit), np.array([end_id], "<u4").tobytes()
    for batch in batches:
        texts = batch.column("text").to_pylist()
        row, piece, start, length, crc = [], [], [], [], []
        for i, parts in enumerate(encoder.values(texts)):
            parts.append(end)
            ids = b"".join(parts)
            for p, a in enumerate(range(0, len(ids), 4 * capacity)):
                part = ids[a : a + 4 * capacity]
                row.append(i)
                piece.append(p)
                start.append(a // 4)
                length.append(len(part) // 4)
                crc.append(zlib.crc32(part))
        yield pa.RecordBatch.from_arrays([batch.column("id").take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())], names=["id", "piece", "start", "length", "ids_crc32"])


def pieces(docs: DataFrame, tokenizer_path: str, capacity: int = 4096, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", spaced: bool = False, limit: int = 600_000) -> DataFrame:
    """(id, piece, start, length, ids_crc32): token sequences, those over capacity cut into pieces.

    A null text is empty: its one piece is the end id alone. Repeated rows give pieces each.
    """
    id_type = docs.schema[id_col].dataType.simpleString()
    texts = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return texts.mapInArrow(lambda b: trimmed(_pieces(b, tokenizer_path, spaced, capacity, end_id, limit)), f"id {id_type}, piece int, start bigint, length bigint, ids_crc32 bigint")


def _evolve(batches: Iterator[pa.RecordBatch], capacity: int, how: Evolution, epoch: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = []
        for shard, island, items, population in zip(*(batch.column(c) for c in ("shard", "island", "items", "population")), strict=True):
            lengths = items.values.field("length").to_numpy().astype(np.int64)
            own = Island(lengths, capacity, how, seed=(shard.as_py() * 31 + island.as_py()) * 31 + epoch)
            found = own.evolve([np.frombuffer(x, np.int32) for x in population.as_py() or []])
            out.append((len(np.unique(found[0])), own.bound, [x.tobytes() for x in found]))
        yield pa.RecordBatch.from_arrays([batch.column("shard"), batch.column("island"), batch.column("items"), pa.array([x[2] for x in out], pa.list_(pa.binary())), pa.array([x[0] for x in out], pa.int32()), pa.array([x[1] for x in out], pa.int32())], names=["shard", "island", "items", "population", "n_bins", "bound"])


def _open_bins(batches: Iterator[pa.RecordBatch], base: int) -> Iterator[pa.RecordBatch]:
    """Best individual of each shard -> a row for each item with its bin's number, offset and fill."""
    for batch in batches:
        for shard, items, best in zip(batch.column("shard").to_pylist(), batch.column("items"), batch.column("best").to_pylist(), strict=True):
            rows = items.values
            bins, lengths = np.frombuffer(best, np.int32), rows.field("length").to_numpy()
            order = np.argsort(bins, kind="stable")
            run = np.cumsum(lengths[order]) - lengths[order]
            first = np.flatnonzero(np.r_[True, np.diff(bins[order]) != 0]) if len(order) else order
            size = np.diff(np.r_[first, len(order)])
            offset = run - np.repeat(run[first], size)
            fill = np.bincount(bins, lengths).astype(np.int64)[bins[order]] if len(order) else bins
            taken = rows.take(pa.array(order))
            columns = [taken.field(n) for n in ("id", "piece", "start", "length", "ids_crc32")]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(base + (int(shard) << 24) + bins[order].astype(np.int64)), pa.array(offset.astype(np.int64)), pa.array(fill)], names=["id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", "fill"])


def _pack(items: DataFrame, n_items: int, capacity: int, how: Evolution, base: int, name: str) -> DataFrame:
    n_shards = max(1, math.ceil(n_items / how.shard_items))
    id_type = items.schema["id"].dataType.simpleString()
    item = "struct<length:bigint,id:%s,piece:int,start:bigint,ids_crc32:bigint>" % id_type
    shard = F.pmod(F.xxhash64("id", "piece", "ids_crc32", F.lit(base)), F.lit(n_shards)).cast("bigint")
    state_type = f"shard bigint, island int, items array<{item}>, population array<binary>, n_bins int, bound int"
    shards = items.groupBy(shard.alias("shard")).agg(F.collect_list(F.struct("length", "id", "piece", "start", "ids_crc32")).alias("items"))
    # all islands would begin alike, so only one sets out; the rest join where it isn't enough
    start = shards.select("shard", F.lit(0).alias("island"), F.array_sort("items").alias("items"), F.lit(None).cast("array<binary>").alias("population"))
    done = materialise(start.mapInArrow(lambda b: trimmed(_evolve(b, capacity, how, 0)), state_type), f"{name}_0")
    best = done.select("shard", "items", "n_bins", "bound", F.col("population")[0].alias("best"))
    state = done.where("n_bins > bound")
    for epoch in range(1, how.epochs + 1):
        if not state.head(1):
            break
        if epoch == 1:
            state = state.withColumn("island", F.explode(F.sequence(F.lit(0), F.lit(how.islands - 1))))
        else:
            moved = state.select("shard", ((F.col("island") + 1) % how.islands).alias("island"), F.slice("population", 1, how.elites).alias("guests"))
            state = state.join(moved, ["shard", "island"]).withColumn("population", F.concat("guests", "population"))
        state = state.repartition("shard", "island").select("shard", "island", "items", "population")
        state = materialise(state.mapInArrow(lambda b, e=epoch: trimmed(_evolve(b, capacity, how, e)), state_type), f"{name}_{epoch}")
        top = state.groupBy("shard").agg(F.min_by("population", F.struct("n_bins", "island")).getItem(0).alias("p"), F.min("n_bins").alias("n"))
        best = best.join(top, "shard", "left").select("shard", "items", F.least("n_bins", F.coalesce("n", "n_bins")).alias("n_bins"), "bound", F.when(F.col("n") < F.col("n_bins"), F.col("p")).otherwise(F.col("best")).alias("best"))
        settled = state.groupBy("shard").agg((F.min("n_bins") > F.min("bound")).alias("open")).where("open").select("shard")
        state = state.join(settled, "shard", "left_semi")
    schema = f"id {id_type}, piece int, start bigint, length bigint, ids_crc32 bigint, sequence_id bigint, offset bigint, fill bigint"
    return materialise(best.select("shard", "items", "best").mapInArrow(lambda b: trimmed(_open_bins(b, base)), schema), f"{name}_packed")


def pack(docs: DataFrame, tokenizer_path: str, capacity: int = 4096, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text", spaced: bool = False, how: Evolution = Evolution()) -> DataFrame:
    """A row for each piece: id, piece, start, length, ids_crc32, sequence_id, offset.

    Sequences hold at most capacity tokens and are filled without gaps from offset 0. Null and
    empty texts take one token, the end id. Repeated rows and ids are packed each on their own;
    an empty table gives no rows; other columns are ignored.
    """
    cut = materialise(pieces(docs, tokenizer_path, capacity, end_id, id_col, text_col, spaced), "pieces")
    packed = _pack(cut, cut.count(), capacity, how, 0, "first")
    poor = packed.where(F.col("fill") < how.poor_fill * capacity)
    n_poor = poor.count()
    if n_poor > 1:
        fields = ["id", "piece", "start", "length", "ids_crc32"]
        again = _pack(poor.select(*fields), n_poor, capacity, how, 1 << 56, "again")
        # the second packing counts only if it saves sequences
        if again.select("sequence_id").distinct().count() < poor.select("sequence_id").distinct().count():
            packed = packed.where(F.col("fill") >= how.poor_fill * capacity).unionByName(again)
    return packed.select(F.col("id").alias(id_col), "piece", "start", "length", "ids_crc32", "sequence_id", "offset")
