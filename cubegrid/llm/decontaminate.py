"""Benchmark decontamination over a distributed positional inverted index.

``build_index`` stores, block by block of documents, the postings of every token: one row per
block with its documents, its terms and their sorted positions. Documents are never split over
blocks, so every later step works within a block and nothing is shuffled. ``phrase_hits`` takes
the benchmark's windows, starts from the postings of each window's rarest term in the block,
shifts them by the term's offset and intersects them with the shifted postings of the next rarest
terms until the whole phrase is matched. ``proximity_hits`` asks for all terms within a span.

The benchmark is read in blocks of windows; one block (``window_block`` windows, a fixed size) is
broadcast at a time, so a large benchmark means more passes over the index, never a larger
broadcast.

Defined results: a null or word-free document has no words, is not hit and not contaminated; a
null or word-free item has no window; repeated documents are each reported; items of equal text
all count; items without an id hit words too, count together as one item and are not in the list of ids;
an empty benchmark hits nothing. Only the named columns are used.
"""

from __future__ import annotations

import uuid
from collections import defaultdict
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubegrid.llm.common import slices, starts_of, stored, tame_arrow, word_bytes, words_of

WINDOW = 13
BLOCK_BYTES = 4 << 20
_INDEX = "block_id string, doc_ids array<long>, text_hashes array<long>, doc_words array<int>, terms array<string>, term_counts binary, positions binary"


# ---- the index ----------------------------------------------------------------------------------


def _block(ids: list[int | None], rows: list[bytes | None]) -> dict:
    """Postings of a block: position p of the block's word sequence; documents follow one another."""
    lists = [word_bytes(t) if t else [] for t in rows]
    lens = np.fromiter(map(len, lists), np.int32, len(lists))
    names: defaultdict[bytes, int] = defaultdict()
    names.default_factory = names.__len__
    term = np.fromiter(map(names.__getitem__, chain.from_iterable(lists)), np.int32, int(lens.sum()))
    order = np.argsort(term, kind="stable").astype(np.int32)
    counts = np.bincount(term, minlength=len(names)).astype(np.int32)
    return {"doc_ids": ids, "doc_words": lens, "terms": pa.array(list(names), pa.binary()).cast(pa.string()), "counts": counts, "positions": order}


def build_index(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row per block of about ``block_bytes`` of text (one document at least)."""
    tame_arrow(docs.sparkSession)
    narrow = docs.select(F.col(doc_id).cast("long").alias("id"), F.col(text).cast("binary").alias("text"), F.xxhash64(text).alias("h"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text", block_bytes):
            b = _block(part.column("id").to_pylist(), part.column("text").to_pylist())
            # gaps within a term compress well; the first is the position itself
            gaps = b["positions"].copy()
            first = starts_of(b["counts"])[:-1]
            gaps[1:] -= b["positions"][:-1]
            gaps[first] = b["positions"][first]
            name = uuid.uuid4().hex  # the index is stored, so a block keeps its name
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([name]),
                    pa.array([b["doc_ids"]], pa.list_(pa.int64())),
                    pa.array([part.column("h").to_pylist()], pa.list_(pa.int64())),
                    pa.array([b["doc_words"]], pa.list_(pa.int32())),
                    pa.ListArray.from_arrays(pa.array([0, len(b["terms"])], pa.int32()), b["terms"]),
                    pa.array([b["counts"].tobytes()]),
                    pa.array([gaps.tobytes()]),
                ],
                names=["block_id", "doc_ids", "text_hashes", "doc_words", "terms", "term_counts", "positions"],
            )

    return narrow.mapInArrow(run, _INDEX)


def _rows(batch: pa.RecordBatch) -> Iterator[dict]:
    """Rows of the index; their terms, as many as a block has different words, stay an Arrow array."""
    at = batch.schema.get_field_index("terms")
    terms = batch.column(at)
    for i, row in enumerate(batch.remove_column(at).to_pylist()):
        yield {**row, "terms": terms[i].values}


class Postings:
    """A block of the index in memory."""

    def __init__(self, row: dict):
        self.doc_ids, self.hashes, self.doc_words = row["doc_ids"], row["text_hashes"], np.asarray(row["doc_words"], np.int64)
        self.counts = np.frombuffer(row["term_counts"], np.int32).astype(np.int64)
        self.first = starts_of(self.counts)
        gaps = np.frombuffer(row["positions"], np.int32).astype(np.int64)
        run = np.cumsum(gaps)
        if len(gaps):
            begin = self.first[:-1]
            run -= np.repeat(run[begin] - gaps[begin], self.counts)
        self.positions = run
        self.terms = row["terms"]
        self.bounds = starts_of(self.doc_words)
        self.total = int(self.bounds[-1])
        #: term * (total + 1) + position, sorted: membership of a shifted position in a list
        self.keys = np.repeat(np.arange(len(self.counts)), self.counts) * (self.total + 1) + self.positions

    def numbers(self, words: list[str]) -> np.ndarray:
        """The number of each word in this block, -1 where it does not occur."""
        found = pc.index_in(pa.array(words, pa.string()), value_set=self.terms)
        return pc.fill_null(found, -1).to_numpy(zero_copy_only=False).astype(np.int64)

    def has(self, term: np.ndarray, at: np.ndarray) -> np.ndarray:
        key = term * (self.total + 1) + at
        i = np.searchsorted(self.keys, key)
        return (i < len(self.keys)) & (self.keys[np.minimum(i, len(self.keys) - 1)] == key)

    def doc_of(self, at: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.bounds, at, "right") - 1


def find_phrases(p: Postings, phrases: np.ndarray, lengths: np.ndarray, vocabulary: list[str], most: int = 1 << 20) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(phrase number, start position) of every occurrence, in portions of bounded size.

    ``phrases`` holds term numbers of ``vocabulary``, one row per phrase, -1 beyond its length.
    """
    if not p.total or not len(phrases):
        return
    local = np.append(p.numbers(vocabulary), -1)
    terms = local[phrases]
    width = phrases.shape[1]
    used = np.arange(width) < lengths[:, None]
    alive = np.flatnonzero(((terms >= 0) | ~used).all(1))
    if not len(alive):
        return
    terms, used, size = terms[alive], used[alive], lengths[alive]
    freq = np.where(used, p.counts[np.maximum(terms, 0)], np.iinfo(np.int64).max)
    rarest = np.argsort(freq, axis=1, kind="stable")
    anchor = rarest[:, 0]
    row = np.arange(len(alive))
    n = freq[row, anchor]
    cuts = np.flatnonzero(np.diff(np.cumsum(n) // most)) + 1
    for part in np.split(row, cuts):
        for lo in range(0, int(n[part].max()), most):  # one list may be longer than a portion
            m = np.clip(n[part] - lo, 0, most)
            who = np.repeat(part, m)
            where = np.arange(len(who)) - np.repeat(starts_of(m)[:-1], m) + lo
            start = p.positions[p.first[terms[who, anchor[who]]] + where] - anchor[who]
            ok = start >= 0
            who, start = who[ok], start[ok]
            for k in range(1, width):
                if not len(who):
                    break
                off = rarest[who, k]
                used_k = k < size[who]
                hit = ~used_k
                hit[used_k] = p.has(terms[who[used_k], off[used_k]], (start + off)[used_k])
                who, start = who[hit], start[hit]
            if len(who):
                doc = p.doc_of(start)
                whole = start + size[who] <= p.bounds[doc + 1]  # a phrase does not reach into the next document
                yield alive[who[whole]], start[whole]


# ---- the benchmark's windows --------------------------------------------------------------------


def windows_of(words: list[str], width: int = WINDOW) -> list[tuple[str, ...]]:
    if not words:
        return []
    if len(words) < width:
        return [tuple(words)]
    return [tuple(words[i : i + width]) for i in range(len(words) - width + 1)]


def _window_blocks(benchmark: DataFrame, item: str, text: str, width: int, window_block: int) -> Iterator[tuple[list[str], np.ndarray, np.ndarray, list[tuple[int, str | None]]]]:
    """Blocks of distinct windows in a fixed form: vocabulary, term numbers, lengths, (window, item)."""
    vocabulary: dict[str, int] = {}
    number: dict[tuple[str, ...], int] = {}
    owners: list[tuple[int, str | None]] = []

    def block():
        table = np.full((len(number), width), -1, np.int64)
        for w, i in number.items():
            table[i, : len(w)] = [vocabulary[t] for t in w]
        return list(vocabulary), table, np.asarray([len(w) for w in number], np.int64), owners

    rows = benchmark.select(F.col(item).cast("string").alias("item"), F.col(text).alias("text")).where("text is not null")
    for row in rows.toLocalIterator():
        for w in dict.fromkeys(windows_of(words_of(row["text"]), width)):
            for t in w:
                vocabulary.setdefault(t, len(vocabulary))
            owners.append((number.setdefault(w, len(number)), row["item"]))
            if len(number) >= window_block:
                yield block()
                vocabulary, number, owners = {}, {}, []
    if number:
        yield block()


_HITS = "doc_id long, text_hash long, seq string, n_words long, spans binary, items array<string>"


def phrase_hits(index: DataFrame, shared: Broadcast, only_hit: bool = False) -> DataFrame:
    """Per document of the index (or those hit): words, hit spans (pairs of int32 word offsets), items
    that occur. ``shared`` is the broadcast of a block of windows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary, phrases, lengths, owner_pairs = shared.value
        owners: dict[int, list[str]] = defaultdict(list)
        for w, item in owner_pairs:
            owners[w].append(item)
        for batch in batches:
            for row in _rows(batch):
                p = Postings(row)
                spans: dict[int, list[tuple[int, int]]] = defaultdict(list)
                items: dict[int, set[str]] = defaultdict(set)
                for who, start in find_phrases(p, phrases, lengths, vocabulary):
                    doc = p.doc_of(start)
                    own = start - p.bounds[doc]
                    for d, w, a, e in zip(doc.tolist(), who.tolist(), own.tolist(), (own + lengths[who]).tolist(), strict=True):
                        spans[d].append((a, e))
                        items[d].update(owners[w])
                docs = sorted(spans) if only_hit else range(len(p.doc_ids))
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([p.doc_ids[d] for d in docs], pa.int64()),
                        pa.array([p.hashes[d] for d in docs], pa.int64()),
                        pa.array([f"{row['block_id']}:{d}" for d in docs], pa.string()),
                        pa.array([int(p.doc_words[d]) for d in docs], pa.int64()),
                        pa.array([_merged(spans[d]).tobytes() if d in spans else b"" for d in docs], pa.binary()),
                        pa.array([sorted(items[d], key=lambda x: (x is None, x or "")) if d in items else [] for d in docs], pa.list_(pa.string())),
                    ],
                    names=["doc_id", "text_hash", "seq", "n_words", "spans", "items"],
                )

    return index.select("block_id", "doc_ids", "text_hashes", "doc_words", "terms", "term_counts", "positions").mapInArrow(run, _HITS)


def _merged(spans: list[tuple[int, int]]) -> np.ndarray:
    out: list[list[int]] = []
    for a, e in sorted(set(spans)):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], e)
        else:
            out.append([a, e])
    return np.asarray(out, np.int32)


def proximity_hits(index: DataFrame, terms: list[str], span: int) -> DataFrame:
    """(doc_id, start, stop): the narrowest stretches of at most ``span`` words that hold all terms."""
    wanted = list(dict.fromkeys(terms))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in _rows(batch):
                p = Postings(row)
                numbers = p.numbers(wanted)
                if not wanted or (numbers < 0).any():
                    continue
                lists = [p.positions[p.first[i] : p.first[i + 1]] for i in numbers.tolist()]
                at = np.concatenate(lists)
                kind = np.repeat(np.arange(len(lists)), [len(x) for x in lists])
                order = np.argsort(at, kind="stable")
                last = [-1] * len(wanted)
                out = []
                for a, k in zip(at[order].tolist(), kind[order].tolist(), strict=True):
                    last[k] = a
                    lo = min(last)
                    if lo >= 0 and a - lo < span and (d := int(p.doc_of(np.asarray([a]))[0])) == int(p.doc_of(np.asarray([lo]))[0]):
                        out.append((p.doc_ids[d], lo - int(p.bounds[d]), a + 1 - int(p.bounds[d])))
                # a stretch that holds a narrower one with the same start is left out
                best: dict[tuple, tuple] = {}
                for d, lo, hi in out:
                    best.setdefault((d, lo), (d, lo, hi))
                found = list(best.values())
                yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in found], pa.int64()) for i in range(3)], names=["doc_id", "start", "stop"])

    return index.mapInArrow(run, "doc_id long, start long, stop long")


# ---- the contamination rule ---------------------------------------------------------------------


def _digest(spark_df: DataFrame) -> DataFrame:
    n_hit = "aggregate(spans, 0L, (a, s) -> a + s.stop - s.start)"
    return spark_df.withColumn("n_hit", F.expr(n_hit)).select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"),
        ((F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"),
        "spans",
        "text_hash",
    )


def _spans_column(hits: DataFrame) -> DataFrame:
    """The packed spans as an array of structs, decoded in an Arrow function."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            packed = [np.frombuffer(x, np.int32).reshape(-1, 2) for x in b.column("spans").to_pylist()]
            lens = np.fromiter(map(len, packed), np.int64, len(packed))
            flat = np.concatenate(packed) if len(packed) else np.zeros((0, 2), np.int32)
            entry = pa.StructArray.from_arrays([pa.array(flat[:, 0]), pa.array(flat[:, 1])], names=["start", "stop"])
            spans = pa.ListArray.from_arrays(pa.array(starts_of(lens).astype(np.int32)), entry)
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in ("doc_id", "text_hash", "seq", "n_words")], spans, b.column("items")], names=["doc_id", "text_hash", "seq", "n_words", "spans", "items"])

    return hits.mapInArrow(run, "doc_id long, text_hash long, seq string, n_words long, spans array<struct<start:int,stop:int>>, items array<string>")


def contamination(docs: DataFrame, benchmark: DataFrame, text: str = "text", doc_id: str = "doc_id", item: str = "item_id", item_text: str = "text", width: int = WINDOW, window_block: int = 200_000) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated, spans, text_hash of every document."""
    spark = docs.sparkSession
    index = stored(build_index(docs, text, doc_id), "postings")
    tame_arrow(spark)
    blocks = _window_blocks(benchmark, item, item_text, width, window_block)
    first = next(blocks, ([], np.zeros((0, width), np.int64), np.zeros(0, np.int64), []))
    shared = spark.sparkContext.broadcast(first)
    more = next(blocks, None)
    if more is None:
        return _digest(_spans_column(phrase_hits(index, shared)))
    # further blocks one after the other, each gone before the next: only documents they hit are kept, and
    # spans and items of a document from several passes are united afterwards
    hits = stored(phrase_hits(index, shared), "phrase-hits")
    while more is not None:
        shared.unpersist()
        shared = spark.sparkContext.broadcast(more)
        hits = hits.unionByName(stored(phrase_hits(index, shared, only_hit=True), "phrase-hits"))
        more = next(blocks, None)
    shared.unpersist()

    def unite(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            spans = [_merged([tuple(s) for x in packed for s in np.frombuffer(x, np.int32).reshape(-1, 2).tolist()]).astype(np.int32).tobytes() for packed in b.column("packed").to_pylist()]
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in ("doc_id", "text_hash", "seq", "n_words")], pa.array(spans, pa.binary()), b.column("items")], names=["doc_id", "text_hash", "seq", "n_words", "spans", "items"])

    index_ids = hits.groupBy("doc_id", "text_hash", "seq", "n_words").agg(F.collect_list("spans").alias("packed"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    return _digest(_spans_column(index_ids.mapInArrow(unite, _HITS)))


def op4_decontamination(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated of every document."""
    from cubegrid.llm.common import table

    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("spans", "text_hash")
