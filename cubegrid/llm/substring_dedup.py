"""Removal of long byte matches, with a run-length index of what is ambiguous.

A byte goes if a ``width``-byte string that covers it also starts in a document with a smaller id.
The corpus is too large for one index, so equal strings are first brought together:

1. Texts are stored in blocks. Within a text, consecutive strings of ``width`` bytes that share
   their minimizer (the k bytes of least hash in them) form one stretch; equal strings always share
   it, and a stretch is a tenth as many records as strings. Blocks send distinct stretches only.
2. Per bucket of minimizers, those that one document alone has are done with. A minimizer whose copies all
   have one and the same stretch is settled at once (``settle`` says why). What is left is minimizers
   with several different stretches, which overlap in part.
3. All copies of those stretches are fetched (where very many share a minimizer, they are cut once more by a
   longer one, which spreads them) and indexed: run-compressed transform, samples at run ends, matching statistics of
   every stretch streamed against it, and the least document of each matched string located from
   the samples.
4. Each block removes what is settled.

Blocks are rows of a stored table and all results return to them by key, so no document is split
over tasks and none is collected. Equal stretches of a block are one record, which pre-aggregates
groups of copies; 96-bit keys stand for stretches.

Defined results: null text is empty; rows with null id lose nothing and are earlier than nobody;
rows with equal ids are not earlier than each other; texts shorter than the width stay whole.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubegrid.llm.common import mix64, slices, starts_of, stored, tame_arrow
from cubegrid.llm.rindex import RunLengthIndex

WIDTH, SHORT, LONG = 50, 24, 40
BLOCK_BYTES = 1 << 20
PORTION = 1 << 16
CROWD = 4096
_BLOCKS = "block long, doc_ids array<long>, lens array<long>, body binary"
_REPLY = "block long, kind int, bucket int, body binary"


# ---- stretches ------------------------------------------------------------------------------------


def _words(data: bytes) -> np.ndarray:
    """The eight bytes at every position as a number."""
    n = len(data) - 7
    out = np.empty(max(n, 0), np.uint64)
    for off in range(min(8, max(n, 0))):
        out[off::8] = np.frombuffer(data, "<u8", (len(data) - off) // 8, off)[: len(out[off::8])]
    return out


def gram_hashes(data: bytes, k: int) -> np.ndarray:
    """Hash of the k bytes (a multiple of eight) at every position."""
    words = _words(data)
    n = len(data) - k + 1
    out = np.zeros(max(n, 0), np.uint64)
    for i in range(0, k, 8):
        out += words[i : i + n]
        out *= np.uint64(0x9FB21C651E98DF25)
        out ^= out >> np.uint64(29)
    return mix64(out)


def stretches(data: bytes, bounds: np.ndarray, width: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(start, strings, text number, minimizer hash) of every stretch of the texts in ``data``.

    Texts are taken in portions that fit the processor's cache.
    """
    cuts = np.flatnonzero(np.diff(bounds[1:] // PORTION, prepend=0)) if len(bounds) > 1 else np.zeros(0, np.int64)
    edges = np.unique(np.concatenate([[0], cuts, [len(bounds) - 1]]))
    parts = []
    for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
        lo, hi = int(bounds[a]), int(bounds[b])
        start, count, text, m = _stretches(data[lo:hi], bounds[a : b + 1] - lo, width, k)
        parts.append((start + lo, count, text + a, m))
    none = np.zeros(0, np.int64)
    return tuple(map(np.concatenate, zip(*parts, strict=True))) if parts else (none, none, none, np.zeros(0, np.uint64))


def _stretches(data: bytes, bounds: np.ndarray, width: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    lens = np.diff(bounds)
    none = np.zeros(0, np.int64)
    if not len(lens) or lens.max() < width:
        return none, none, none, np.zeros(0, np.uint64)
    hashes = gram_hashes(data, k)
    low = np.uint64((1 << 31) - 1)
    least = hashes & ~low
    least |= np.arange(len(hashes), dtype=np.uint64)
    span, have = width - k + 1, 1
    while 2 * have <= span:
        least = np.minimum(least[:-have], least[have:])
        have *= 2
    if have < span:
        gap = span - have
        least = np.minimum(least[:-gap], least[gap:])
    least &= low
    place = least.view(np.int64)  # of the minimizer of the string at each position
    # a stretch ends where the minimizer changes and at the last string of a text
    change = np.ones(len(place), bool)
    np.not_equal(place[1:], place[:-1], out=change[1:])
    texts = np.flatnonzero(lens >= width)
    first, last = bounds[:-1][texts], bounds[1:][texts] - width
    inside = np.zeros(len(place) + 1, np.int8)
    np.add.at(inside, first, 1)
    np.add.at(inside, last + 1, -1)
    change[first] = True
    start = np.flatnonzero(change & (np.cumsum(inside[:-1]) > 0))
    text = np.searchsorted(first, start, "right") - 1
    stop = np.minimum(np.append(start[1:], len(place)), last[text] + 1)
    return start, stop - start, texts[text], hashes[place[start]]


def stretch_keys(data: bytes, start: np.ndarray, stop: np.ndarray, width: int, k: int) -> np.ndarray:
    """64-bit key of the content of every stretch: all its eight-byte words from the front, those of
    the rest from the back, and its length."""
    if not len(start):
        return np.zeros(0, np.uint64)
    words = _words(data)
    front = width // 8
    back = -(-(2 * width - k - 8 * front) // 8)
    out = (stop - start).astype(np.uint64)
    for at in [*(start + 8 * i for i in range(front)), *(stop - 8 * (i + 1) for i in range(back))]:
        out ^= words[at]
        out *= np.uint64(0x9FB21C651E98DF25)
        out ^= out >> np.uint64(29)
    return mix64(out)


class Block:
    """The texts of one block and their distinct stretches, in an order that can be made again."""

    def __init__(self, doc_ids: list[int | None], lens: list[int], data: bytes, buckets: int, width: int, k: int):
        self.data, self.bounds, self.width = data, starts_of(np.asarray(lens, np.int64)), width
        self.known = np.asarray([d is not None for d in doc_ids], bool)
        self.ids = np.asarray([d if d is not None else 0 for d in doc_ids], np.int64)
        start, count, text, m = stretches(data, self.bounds, width, k)
        keep = self.known[text] if len(text) else np.zeros(0, bool)
        self.start, self.count, self.text, m = start[keep], count[keep], text[keep], m[keep]
        key = stretch_keys(data, self.start, self.start + self.count + (width - 1), width, k)
        self.doc = self.ids[self.text] if len(self.text) else np.zeros(0, np.int64)
        order = np.argsort(key)
        first = np.zeros(len(order), bool)
        if len(order):  # equal in key and minimizer
            other_key, other_m = key[order][1:] != key[order][:-1], m[order][1:] != m[order][:-1]
            if (other_m & ~other_key).any():  # a clash of keys, to be taken apart
                order = np.lexsort((m, key))
                other_key, other_m = key[order][1:] != key[order][:-1], m[order][1:] != m[order][:-1]
            first = np.concatenate([[True], other_key | other_m])
        self.unique = np.empty(len(order), np.int64)
        self.unique[order] = np.cumsum(first) - 1
        # of each distinct stretch, its place in the smallest document: texts stand in order of their ids
        lead = np.minimum.reduceat(order, np.flatnonzero(first)) if len(order) else order
        self.u_key, self.u_min, self.u_doc, self.u_start, self.u_count = key[lead], m[lead], self.doc[lead], self.start[lead], self.count[lead]
        self.u_bucket = (self.u_min % np.uint64(buckets)).astype(np.int64)
        self.by_bucket = np.argsort(self.u_bucket * (len(order) + 1) + lead)

    def portions(self) -> Iterator[tuple[int, np.ndarray]]:
        b = self.u_bucket[self.by_bucket]
        cuts = np.flatnonzero(np.diff(b)) + 1
        for part in np.split(self.by_bucket, cuts):
            if len(part):
                yield int(self.u_bucket[part[0]]), part


def _pack(values: np.ndarray, n: int) -> bytes:
    """The lowest n bytes of each number."""
    return np.ascontiguousarray(values.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :n]).tobytes()


def _unpack(body: bytes, n: int) -> np.ndarray:
    raw = np.frombuffer(body, np.uint8).reshape(-1, n)
    out = np.zeros((len(raw), 8), np.uint8)
    out[:, :n] = raw
    return out.view("<u8").ravel()


def _open(row: dict, buckets: int, width: int) -> Block:
    import zstandard

    return Block(row["doc_ids"], row["lens"], zstandard.decompress(row["body"]) if row["body"] else b"", buckets, width, SHORT)


def text_blocks(docs: DataFrame, text: str, doc_id: str, block_bytes: int) -> DataFrame:
    """Texts in blocks of about ``block_bytes`` (one text at least), compressed."""
    tame_arrow(docs.sparkSession)
    narrow = docs.select(F.col(doc_id).cast("long").alias("id"), F.coalesce(F.col(text), F.lit("")).cast("binary").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        for part in slices(batches, "text", block_bytes):
            part = part.take(pc.sort_indices(part.column("id"), null_placement="at_start"))
            rows = part.column("text").to_pylist()
            body = b"".join(rows)
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([uuid.uuid4().int >> 65], pa.int64()),  # kept: the table is stored
                    pa.array([part.column("id").to_pylist()], pa.list_(pa.int64())),
                    pa.array([[len(r) for r in rows]], pa.list_(pa.int64())),
                    pa.array([zstandard.compress(body, 3) if body else b""], pa.binary()),
                ],
                names=["block", "doc_ids", "lens", "body"],
            )

    return narrow.mapInArrow(run, _BLOCKS)


# ---- bringing equal stretches together --------------------------------------------------------------


def _send_stretches(blocks: DataFrame, buckets: int, width: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                b = _open(row, buckets, width)
                out = [(row["block"], bucket, _pack(b.u_min[u], 5), _pack(b.u_key[u], 7), zlib.compress(np.diff(b.u_doc[u], prepend=0).tobytes(), 1)) for bucket, u in b.portions()]
                yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], t) for i, t in enumerate((pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary()))], names=["block", "bucket", "m", "key", "docs"])

    return blocks.mapInArrow(run, "block long, bucket int, m binary, key binary, docs binary")


def settle(m: np.ndarray, key: np.ndarray, doc: np.ndarray, crowd: int = CROWD, alone: bool = False) -> np.ndarray:
    """Per record: 0 if no other document has its minimizer, 2 or 3 if its strings must be looked up
    (3: so many different stretches share the minimizer that they are cut by a longer one).

    A minimizer with one stretch only would make an index of that one text, in which its strings have
    the least document of its copies: 1 says so at once where a smaller document has it, unless ``alone``
    asks for the index there too.
    """
    out = np.zeros(len(m), np.uint8)
    order = np.argsort(m)
    same = m[order[1:]] == m[order[:-1]]
    order = order[np.append(same, False) | np.concatenate([[False], same])]  # most records are alone
    if not len(order):
        return out
    order = order[np.lexsort((key[order], m[order]))]
    m, key, d = m[order], key[order], doc[order]
    new_m = np.concatenate([[True], m[1:] != m[:-1]])
    new = new_m | np.concatenate([[True], key[1:] != key[:-1]])
    kind = np.cumsum(new) - 1
    group = np.cumsum(new_m) - 1
    at = np.flatnonzero(new_m)
    lo, hi = np.minimum.reduceat(d, at), np.maximum.reduceat(d, at)
    size = np.diff(np.append(kind[at], kind[-1] + 1))  # distinct stretches
    status = np.where(lo < hi, np.where(size > crowd, 3, 2), 0)[group]
    if not alone:
        single = (size == 1)[group]
        status[single] = d[single] > lo[group][single]
    out[order] = status
    return out


def _settled(sent: DataFrame, crowd: int, alone: bool) -> DataFrame:
    def run(group: pa.Table) -> pa.Table:
        m = [_unpack(x, 5) for x in group.column("m").to_pylist()]
        key = [_unpack(x, 7) for x in group.column("key").to_pylist()]
        doc = [np.cumsum(np.frombuffer(zlib.decompress(x), np.int64)) for x in group.column("docs").to_pylist()]
        status = settle(np.concatenate(m), np.concatenate(key), np.concatenate(doc), crowd, alone)
        cuts = starts_of(np.asarray([len(x) for x in m]))
        body = [zlib.compress(status[a:b].tobytes(), 1) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
        return pa.table({"block": group.column("block"), "kind": pa.array([1] * len(m), pa.int32()), "bucket": group.column("bucket"), "body": pa.array(body, pa.binary())})

    return sent.groupBy("bucket").applyInArrow(run, _REPLY)


# ---- looking up ambiguous strings ---------------------------------------------------------------------


def _statuses(b: Block, replies: dict[int, bytes]) -> np.ndarray:
    out = np.zeros(len(b.u_key), np.uint8)
    for bucket, u in b.portions():
        out[u] = np.frombuffer(zlib.decompress(replies[bucket]), np.uint8)
    return out


class Lookup:
    """The ambiguous stretches of a block, crowded ones cut by the longer minimizer, in an order that can be made again."""

    def __init__(self, b: Block, status: np.ndarray, buckets: int):
        self.u = np.flatnonzero(status >= 2)
        size = b.u_count[self.u] + (b.width - 1)
        self.bounds = starts_of(size)
        self.data = b"".join([b.data[s : s + n] for s, n in zip(b.u_start[self.u].tolist(), size.tolist(), strict=True)])
        few = status[self.u] == 2  # these go whole, by the minimizer they have
        start, count, text, m = stretches(self.data, self.bounds, b.width, LONG) if not few.all() else (few.nonzero()[0][:0],) * 3 + (np.zeros(0, np.uint64),)
        cut = ~few[text]
        whole = np.flatnonzero(few)
        self.start = np.concatenate([self.bounds[whole], start[cut]])
        self.count = np.concatenate([b.u_count[self.u[whole]], count[cut]])
        self.text = np.concatenate([whole, text[cut]])
        self.bucket = (np.concatenate([b.u_min[self.u[whole]], m[cut]]) // np.uint64(3) % np.uint64(buckets)).astype(np.int64)
        self.order = np.argsort(self.bucket, kind="stable")

    def portions(self) -> Iterator[tuple[int, np.ndarray]]:
        cuts = np.flatnonzero(np.diff(self.bucket[self.order])) + 1
        for part in np.split(self.order, cuts):
            if len(part):
                yield int(self.bucket[part[0]]), part


def _replies(table: pa.Table, kind: int) -> dict[int, bytes]:
    return {b: x for k, b, x in zip(table.column("kind").to_pylist(), table.column("bucket").to_pylist(), table.column("body").to_pylist(), strict=True) if k == kind}


def _send_lookups(blocks: DataFrame, replies: DataFrame, buckets: int, long_buckets: int, width: int) -> DataFrame:
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out = []
        answers = _replies(right, 1)
        for row in left.to_pylist():
            b = _open(row, buckets, width)
            look = Lookup(b, _statuses(b, answers), long_buckets)
            for bucket, part in look.portions():
                body = b"".join([look.data[s : s + n + width - 1] for s, n in zip(look.start[part].tolist(), look.count[part].tolist(), strict=True)])
                out.append((row["block"], bucket, b.u_doc[look.u[look.text[part]]].tobytes(), look.count[part].astype(np.uint8).tobytes(), body))
        return pa.Table.from_arrays([pa.array([x[i] for x in out], t) for i, t in enumerate((pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary()))], names=["block", "bucket", "docs", "counts", "body"])

    return blocks.groupBy("block").cogroup(replies.groupBy("block")).applyInArrow(run, "block long, bucket int, docs binary, counts binary, body binary")


def look_up(data: bytes, lens: np.ndarray, docs: np.ndarray, width: int) -> np.ndarray:
    """Per string of ``width`` bytes of the given texts, in order: whether a text of a smaller document has it."""
    bounds = starts_of(lens)
    # equal texts are one text of the index, with their least document
    number: dict[bytes, int] = {}
    which = np.fromiter((number.setdefault(data[a:b], len(number)) for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)), np.int64, len(lens))
    owner = np.full(len(number), np.iinfo(np.int64).max)
    np.minimum.at(owner, which, docs)
    joined = np.frombuffer(b"".join(number), np.uint8)
    sizes = np.fromiter(map(len, number), np.int64, len(number))
    index = RunLengthIndex(joined, sizes, width)
    matched, interval = index.stream(joined, sizes)
    met = np.zeros(len(index.open_row), bool)
    met[interval[interval >= 0]] = True
    asked = np.flatnonzero(met)
    best = np.full(len(met), np.iinfo(np.int64).max)
    best[asked] = index.least(asked, owner)
    first = starts_of(sizes)[:-1]
    strings = lens - width + 1
    own = np.arange(int(strings.sum())) - np.repeat(starts_of(strings)[:-1], strings)
    at = np.repeat(first[which], strings) + own
    return (matched[at] >= width) & (best[interval[at]] < np.repeat(docs, strings))


def _looked_up(sent: DataFrame, width: int) -> DataFrame:
    def run(group: pa.Table) -> pa.Table:
        counts = [np.frombuffer(x, np.uint8).astype(np.int64) for x in group.column("counts").to_pylist()]
        docs = np.concatenate([np.frombuffer(x, np.int64) for x in group.column("docs").to_pylist()])
        hit = look_up(b"".join(group.column("body").to_pylist()), np.concatenate(counts) + width - 1, docs, width)
        cuts = starts_of(np.asarray([int(c.sum()) for c in counts]))
        body = [zlib.compress(np.packbits(hit[a:b]).tobytes(), 1) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
        return pa.table({"block": group.column("block"), "kind": pa.array([2] * len(counts), pa.int32()), "bucket": group.column("bucket"), "body": pa.array(body, pa.binary())})

    return sent.groupBy("bucket").applyInArrow(run, _REPLY)


# ---- removal ------------------------------------------------------------------------------------------


def covered(b: Block, status: np.ndarray, look: Lookup | None, answers: dict[int, bytes]) -> np.ndarray:
    """Which bytes of the block go."""
    edge = np.zeros(len(b.data) + 1, np.int32)
    whole = (status[b.unique] == 1) | (b.doc > b.u_doc[b.unique]) if len(b.unique) else np.zeros(0, bool)
    np.add.at(edge, b.start[whole], 1)
    np.add.at(edge, b.start[whole] + b.count[whole] + (b.width - 1), -1)
    if look is not None and len(look.u):
        size = b.u_count[look.u]
        first = starts_of(size)
        flags = np.zeros(int(first[-1]), bool)  # per string of each ambiguous stretch
        for bucket, part in look.portions():
            n = int(look.count[part].sum())
            hit = np.unpackbits(np.frombuffer(zlib.decompress(answers[bucket]), np.uint8), count=n).astype(bool)
            own = np.arange(n) - np.repeat(starts_of(look.count[part])[:-1], look.count[part])
            flags[np.repeat(first[look.text[part]] + look.start[part] - look.bounds[look.text[part]], look.count[part]) + own] = hit
        slot = np.full(len(b.u_key), -1, np.int64)
        slot[look.u] = np.arange(len(look.u))
        mine = np.flatnonzero((slot[b.unique] >= 0) & ~whole)  # every place of the stretch in its first document
        k = b.count[mine]
        own = np.arange(int(k.sum())) - np.repeat(starts_of(k)[:-1], k)
        hit = flags[np.repeat(first[slot[b.unique[mine]]], k) + own]
        at = (np.repeat(b.start[mine], k) + own)[hit]
        np.add.at(edge, at, 1)
        np.add.at(edge, at + b.width, -1)
    return np.cumsum(edge[:-1]) > 0


def remove_repeats(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", width: int = WIDTH, block_bytes: int = BLOCK_BYTES, bucket_bytes: int = 12 << 20, crowd: int = CROWD, keep_text: bool = True, alone: bool = False) -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256 and, if wanted, the kept bytes."""
    if width < LONG + 1:
        raise ValueError(f"matches of {LONG + 1} bytes or more")
    blocks = stored(text_blocks(docs, text, doc_id, block_bytes), "text-blocks")
    total = blocks.agg(F.coalesce(F.sum(F.expr("aggregate(lens, 0L, (a, x) -> a + x)")), F.lit(0))).first()[0]
    buckets, long_buckets = 1 + total // bucket_bytes, 1 + 4 * total // bucket_bytes
    settled = stored(_settled(_send_stretches(blocks, buckets, width), crowd, alone), "settled")
    looked = stored(_looked_up(_send_lookups(blocks, settled, buckets, long_buckets, width), width), "looked-up")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        one, two = _replies(right, 1), _replies(right, 2)
        out = []
        for row in left.to_pylist():
            b = _open(row, buckets, width)
            status = _statuses(b, one)
            gone = covered(b, status, Lookup(b, status, long_buckets), two)
            raw = np.frombuffer(b.data, np.uint8)
            for d, lo, hi in zip(row["doc_ids"], b.bounds[:-1].tolist(), b.bounds[1:].tolist(), strict=True):
                g = gone[lo:hi]
                n = int(g.sum())
                kept = b.data[lo:hi] if not n else raw[lo:hi][~g].tobytes()
                spans = int(g[:1].sum() + (g[1:] & ~g[:-1]).sum()) if n else 0
                out.append((d, hi - lo, n, spans, hashlib.sha256(kept).hexdigest(), kept if keep_text else None))
        kinds = [pa.int64()] * 4 + [pa.string(), pa.binary()]
        return pa.Table.from_arrays([pa.array([x[i] for x in out], kinds[i]) for i in range(6)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    replies = settled.unionByName(looked)
    got = blocks.groupBy("block").cogroup(replies.groupBy("block")).applyInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
    return got if keep_text else got.drop("kept")


def op8_substring_dedup(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every document."""
    from cubegrid.llm.common import table

    return remove_repeats(table(spark, sf_dir, "documents"), keep_text=False)
