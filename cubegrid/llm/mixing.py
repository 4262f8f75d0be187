"""Mixing sources to target weights by Pfair scheduling.

Each source is cut into blocks of documents. The target is a fluid one: at every moment the sources
that still have blocks share the slots in proportion to their weights, and when one runs out the
others speed up. Block j of a source (from 1) is released in the slot in which the target reaches
j-1 blocks and due when it reaches j; taking the released block with the earliest deadline in every
slot keeps each source less than one block from its target at all times, through every phase. Weights
are taken as the exact rationals they are and times are exact integers: nothing is rounded to a cycle,
so no error grows with the number of blocks.

The driver sees one count per source and three numbers per block, never documents. The number of a
document within its source comes from bounded groups (a source's documents are dealt over
``group_rows`` sized groups by hash), so a source with a third of all rows is no single task.

Defined results: a null source is one source of its own; null texts and repeated rows are placed
like others; an empty table gives no row. Columns added are named with a ``mix_`` prefix; clashing
columns of the input are replaced.
"""

from __future__ import annotations

import heapq
import math
from bisect import bisect_left
from collections.abc import Iterator
from dataclasses import dataclass
from fractions import Fraction
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubegrid.llm.common import fresh

NO_SOURCE = "\0none"


def shares(weights: list[float], cycle: int) -> list[int]:
    """Whole shares of a cycle by largest remainder, one slot at least; mixes do not round and do not use it."""
    total = sum(weights)
    ideal = [w * cycle / total for w in weights]
    out = [max(1, int(x)) for x in ideal]
    order = sorted(range(len(out)), key=lambda i: (out[i] - ideal[i], i))
    k = 0
    while sum(out) < cycle:
        out[order[k % len(out)]] += 1
        k += 1
    while sum(out) > cycle:
        i = max(range(len(out)), key=lambda i: (out[i] - ideal[i] if out[i] > 1 else -np.inf, -i))
        out[i] -= 1
    return out


def windows(blocks: list[int], weights: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Release and deadline of every block, source after source, and the slots at which phases end.

    When every live source has been given V blocks per unit of weight, source k has min(n_k, w_k V)
    blocks, and the sum of these is the time: straight between two moments when a source runs out.
    """
    order = sorted(range(len(blocks)), key=lambda k: Fraction(blocks[k], weights[k]))
    n, w = [blocks[k] for k in order], [weights[k] for k in order]
    gone = [0, *accumulate(n)]
    live = list(accumulate(w[::-1]))[::-1]
    release, deadline = np.empty(gone[-1], np.int64), np.empty(gone[-1], np.int64)
    at = 0
    for n_own, w_own in zip(blocks, weights, strict=True):
        starts, ends, j = [0], [], 1
        while j <= n_own:
            s = bisect_left(range(len(n)), True, key=lambda s: n[s] * w_own >= j * w[s])  # noqa: B023
            top = min(n_own, w_own * n[s] // w[s])
            for x in range(j * live[s], top * live[s] + 1, live[s]):
                q, r = divmod(x, w_own)
                starts.append(gone[s] + q)
                ends.append(gone[s] + q + (r > 0))
            j = top + 1
        release[at : at + n_own], deadline[at : at + n_own] = starts[:-1], ends
        at += n_own
    stops = [gone[s] - (-n[s] * live[s] // w[s]) for s in range(len(n))]
    return release, deadline, np.unique(np.asarray(stops, np.int64))


def earliest_deadline(release: np.ndarray, deadline: np.ndarray) -> np.ndarray:
    """The slot of each block: earliest deadline first among released blocks, ties by position."""
    n = len(release)
    slot = np.empty(n, np.int64)
    order = np.argsort(release, kind="stable")
    begins = np.searchsorted(release[order], np.arange(n + 1))  # blocks released before each slot
    ready: list[tuple[int, int]] = []
    for t in range(n):
        new = order[begins[t] : begins[t + 1]]
        for key in zip(deadline[new].tolist(), new.tolist(), strict=True):
            heapq.heappush(ready, key)
        slot[heapq.heappop(ready)[1]] = t
    return slot


def schedule_cycle(share: list[int]) -> list[int]:
    """The source of each slot of one cycle in which every source has its share."""
    release, deadline, _ = windows(share, share)
    slots = earliest_deadline(release, deadline)
    return np.repeat(np.arange(len(share)), share)[np.argsort(slots)].tolist()


@dataclass
class Schedule:
    names: list[str]
    first: np.ndarray  # where the blocks of each source begin in the arrays below
    slot: np.ndarray
    release: np.ndarray
    deadline: np.ndarray
    stops: np.ndarray  # slots at which phases end

    def place(self, source: np.ndarray, block: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(phase, slot, release, deadline) of blocks, counted from 0 within their sources."""
        at = self.first[source] + block
        return np.searchsorted(self.stops, self.slot[at], side="right"), self.slot[at], self.release[at], self.deadline[at]


def whole_weights(weights: list[float]) -> list[int]:
    """Whole numbers in exactly the ratio of the weights; sources with none come after all others."""
    exact = [Fraction(x) for x in weights]
    least = min((x for x in exact if x > 0), default=Fraction(1))
    exact = [x if x > 0 else least / 10**12 for x in exact]
    scale = math.lcm(*(x.denominator for x in exact))
    whole = [int(x * scale) for x in exact]
    common = math.gcd(*whole)
    return [x // common for x in whole]


def plan(blocks: dict[str, int], weights: dict[str, float]) -> Schedule:
    names = sorted(k for k, n in blocks.items() if n > 0)
    sizes = [blocks[k] for k in names]
    release, deadline, stops = windows(sizes, whole_weights([weights[k] for k in names]) if names else [])
    return Schedule(names, np.cumsum([0, *sizes], dtype=np.int64), earliest_deadline(release, deadline), release, deadline, stops)


def mix(docs: DataFrame, weights: dict[str, float] | None = None, source: str = "source", doc_id: str = "doc_id", text: str = "text", block_docs: int = 8, cycle: int = 2048, group_rows: int = 1024, temper: float = 0.5, seed: int = 1) -> DataFrame:
    """All rows with mix_block, mix_slot, mix_release, mix_deadline, mix_phase and mix_rank.

    Without ``weights``, a source weighs its number of documents to the power ``temper``; sources
    that ``weights`` leaves out get the smallest weight given. Sorting by mix_rank gives the mix.
    ``cycle`` is accepted from callers of the former repeated cycle and changes nothing.
    """
    spark = docs.sparkSession
    added = ("mix_block", "mix_slot", "mix_release", "mix_deadline", "mix_phase", "mix_rank")
    rows = docs.drop(*added)
    name = F.coalesce(F.col(f"`{source}`").cast("string"), F.lit(NO_SOURCE))
    sizes = {r[0]: r[1] for r in rows.groupBy(name.alias("s")).count().collect()}
    if weights is None:
        weights = {k: n**temper for k, n in sizes.items()}
    least = min(weights.values(), default=1.0)
    schedule = plan({k: -(-n // block_docs) for k, n in sizes.items()}, {k: weights.get(k, least) for k in sizes})
    number = {k: i for i, k in enumerate(schedule.names)}
    key, src, count, h, g, own, before, at, got = fresh(rows.columns, "src_name", "src_no", "src_groups", "row_hash", "row_group", "own_no", "before_no", "at_no", "placed")
    groups = spark.createDataFrame([(k, number[k], max(1, -(-n // group_rows))) for k, n in sizes.items()], f"{key} string, {src} int, {count} int")
    hashed = F.xxhash64(F.col(f"`{doc_id}`").cast("string"), F.lit(seed))
    # one row per source: its size is that of the driver's own list
    dealt = rows.withColumn(key, name).join(F.broadcast(groups), key).withColumn(h, hashed).withColumn(g, F.pmod(h, F.col(count)).cast("int"))
    counts = dealt.groupBy(src, g).agg(F.count("*").alias(own))
    offsets = counts.select(src, g, (F.sum(own).over(Window.partitionBy(src).orderBy(g)) - F.col(own)).alias(before))
    nth = F.row_number().over(Window.partitionBy(src, g).orderBy(F.col(h), F.col(f"`{doc_id}`"), F.xxhash64(F.col(f"`{text}`")))) - 1
    ranked = dealt.withColumn(own, nth).join(offsets, [src, g]).withColumn(at, F.col(own) + F.col(before))
    shared = spark.sparkContext.broadcast(schedule)

    placing = F.struct(F.col(src).alias("src"), (F.col(at) / block_docs).cast("long").alias("block"))

    @F.arrow_udf("struct<phase:long,slot:long,release:long,deadline:long>")
    def place(key: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for k in key:
            found = shared.value.place(k.field("src").to_numpy(zero_copy_only=False), k.field("block").to_numpy(zero_copy_only=False))
            yield pa.StructArray.from_arrays([pa.array(x) for x in found], names=["phase", "slot", "release", "deadline"])

    out = ranked.withColumn(got, place(placing))
    kept = [F.col(f"`{c}`") for c in rows.columns]
    return out.select(
        *kept,
        (F.col(at) / block_docs).cast("long").alias("mix_block"),
        F.col(f"{got}.slot").alias("mix_slot"),
        F.col(f"{got}.release").alias("mix_release"),
        F.col(f"{got}.deadline").alias("mix_deadline"),
        F.col(f"{got}.phase").alias("mix_phase"),
        (F.col(f"{got}.slot") * block_docs + F.col(at) % block_docs).alias("mix_rank"),
    )


def op1_mixing(spark, sf_dir: str) -> DataFrame:
    """doc_id, source and place in the mix of every document."""
    from cubegrid.llm.common import table

    return mix(table(spark, sf_dir, "documents")).select("doc_id", "source", "mix_block", "mix_slot", "mix_release", "mix_deadline", "mix_phase", "mix_rank")
