"""N-gram Jaccard join: MinHash banding, shuffle on band hashes, verification on full n-gram sets.

1. Every text becomes its set of hashed five-word shingles, a 128-bit key of that set and band
   hashes of its MinHash signature; rows per band follow from the threshold and target recall.
   Texts with equal sets are copies (Jaccard 1) and are one representative from here on.
2. Representatives meet in buckets of equal band hash. Buckets up to ``small`` members give pairs,
   which are made distinct and verified on the full sets of both sides.
3. Members of larger buckets are put into families (connected by such buckets), families are cut
   into blocks, and each pair of blocks is one group in which pairs are compared as a matrix
   product: what leaves it is one link count per member and a spanning forest, never all pairs.
4. Links give classes by distributed connected components.

A link is a pair that shares a band and whose full sets reach the threshold: families count
the same pairs as small buckets do, so ``small`` and ``block`` change the cost and never the result. Texts
are not shuffled: the sets of the representatives that are compared are made where their texts lie, found
by a bitmap of their ids (of at most ``_MOST_BITS`` bits; too full a bitmap costs work, not results).

Families cost blocks x members of shipped sets, so a family of very many different texts that all
share a band is the expensive case; copies of equal sets never are.

Defined results: texts of 1 to 4 words have one shingle of all their words; texts without words
are copies of each other only if their raw texts are equal; null texts are each a class of their
own, without links; repeated rows count as copies. Only the named columns are used.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubegrid.llm.common import WordIds, fresh, join_hot, mix64, slices, stored, tame_arrow, texts, words_of
from cubegrid.llm.components import components

SHINGLE = 5
_POWERS = np.asarray([pow(0x9E3779B97F4A7C15, k, 1 << 64) for k in range(SHINGLE)], np.uint64)


def bands_for(threshold: float, recall: float = 0.99999, most_hashes: int = 160) -> tuple[int, int]:
    """(bands, rows): the most selective rows whose bands reach the recall within the hash budget."""
    best = None
    for rows in range(1, 33):
        chance = threshold**rows
        bands = 1 if chance >= 1 else math.ceil(math.log(1 - recall) / math.log(1 - chance))
        if bands * rows <= most_hashes or best is None:
            best = (bands, rows)
        else:
            break
    return best


@cache
def _permutations(n: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20240101)
    return rng.integers(0, 1 << 31, n, dtype=np.uint32) * np.uint32(2) + np.uint32(1), rng.integers(0, 1 << 32, n, dtype=np.uint32)


def shingle_set(text: str, ids: WordIds, n: int = SHINGLE) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's n-word shingles."""
    h = ids.array(words_of(text))
    if not len(h):
        return h
    width = min(n, len(h))
    count = len(h) - width + 1
    out = np.full(count, width, np.uint64)
    for k in range(width):
        out += h[k : k + count] * _POWERS[k]
    return np.unique(mix64(out))


def band_hashes(shingles: np.ndarray, bands: int, rows: int) -> np.ndarray:
    a, b = _permutations(bands * rows)
    x = (shingles >> np.uint64(32)).astype(np.uint32) ^ shingles.astype(np.uint32)
    low = np.full(bands * rows, 0xFFFFFFFF, np.uint32)
    for lo in range(0, len(x), 512):
        np.minimum(low, (x[lo : lo + 512, None] * a + b).min(0), out=low)
    grid = low.reshape(bands, rows).astype(np.uint64)
    out = np.arange(bands, dtype=np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)
    for r in range(rows):
        out = mix64((out ^ grid[:, r]) * np.uint64(0x9E3779B97F4A7C15))
    return out.view(np.int64)


def set_key(text: str | None, shingles: np.ndarray, serial: bytes) -> bytes:
    from xxhash import xxh3_128_digest

    if text is None:
        return serial
    return xxh3_128_digest(shingles.tobytes(), 1) if len(shingles) else xxh3_128_digest(text.encode("utf-8", "surrogatepass"), 2)


def signatures(docs: DataFrame, text: str, doc_id: str, bands: int, rows: int) -> DataFrame:
    """d, h (hash of the text), key, n (shingles) and bands of every row."""
    narrow = docs.select(F.col(f"`{doc_id}`").cast("long").alias("d"), F.xxhash64(F.col(f"`{text}`")).alias("h"), F.col(f"`{text}`").alias("text"), F.monotonically_increasing_id().alias("u"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = WordIds()
        for part in slices(batches, "text"):
            keys, sizes, found = [], [], []
            for t, u in zip(texts(part), part.column("u").to_pylist(), strict=True):
                s = shingle_set(t, ids) if t else np.zeros(0, np.uint64)
                keys.append(set_key(t, s, b"null" + u.to_bytes(12, "big")))
                sizes.append(len(s))
                found.append(band_hashes(s, bands, rows) if len(s) else None)
            yield pa.RecordBatch.from_arrays([part.column("d"), part.column("h"), pa.array(keys, pa.binary()), pa.array(sizes, pa.int32()), pa.array(found, pa.list_(pa.int64()))], names=["d", "h", "key", "n", "bands"])

    return narrow.mapInArrow(run, "d long, h long, key binary, n int, bands array<long>")


#: Bits of the bitmap of wanted ids: sixteen for each id, within these bounds (128 MB).
_LEAST_BITS, _MOST_BITS = 1 << 20, 1 << 30


def _bitmap(ids: DataFrame, bits: int) -> np.ndarray:
    """Bytes of a bitmap in which the slot of every id (column d) is set, built in parts of 32,768 bits."""
    slot = _slot(F.col("d"), bits)
    parts = ids.groupBy(F.bitmap_bucket_number(slot).alias("part")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(slot)).alias("bits"))
    out = np.zeros(bits // 8 + 4096, np.uint8)
    for part, found in parts.toLocalIterator():
        at = (part - 1) * 4096
        out[at : at + 4096] |= np.frombuffer(found, np.uint8)
    return out


def _slot(d: Column, bits: int) -> Column:
    return F.pmod(F.xxhash64(d), F.lit(bits)) + 1


def _sets(docs: DataFrame, wanted: DataFrame, text: str, doc_id: str) -> DataFrame:
    """(key, shingles) of the representatives in ``wanted`` (key, d): one row each."""
    n = wanted.count()
    bits = min(max(_LEAST_BITS, 1 << (16 * n).bit_length()), _MOST_BITS)
    shared = docs.sparkSession.sparkContext.broadcast(_bitmap(wanted, bits))
    body = docs.select(F.col(f"`{doc_id}`").cast("long").alias("d"), F.col(f"`{text}`").alias("text")).where("text is not null").withColumn("slot", _slot(F.col("d"), bits) - 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, bitmap = WordIds(), shared.value
        for batch in batches:
            slot = batch.column("slot").to_numpy(zero_copy_only=False)
            hit = bitmap[slot >> 3] >> (slot & 7).astype(np.uint8) & 1
            for part in slices(iter([batch.filter(pa.array(hit.astype(bool)))]), "text"):
                ds, keys, out = [], [], []
                for d, t in zip(part.column("d").to_pylist(), texts(part), strict=True):
                    s = shingle_set(t, ids)
                    ds.append(d)
                    keys.append(set_key(t, s, b""))
                    out.append(s.tobytes())
                yield pa.RecordBatch.from_arrays([pa.array(ds, pa.int64()), pa.array(keys, pa.binary()), pa.array(out, pa.binary())], names=["d", "key", "shingles"])

    made = body.mapInArrow(run, "d long, key binary, shingles binary")
    asked = wanted.select(F.col("key").alias("k2"), F.col("d").alias("d2"))
    # another row may bear the same id, or an id that falls on a wanted slot
    met = made.join(asked, (F.col("key") == F.col("k2")) & F.col("d").eqNullSafe(F.col("d2")), "left_semi")
    return met.groupBy("key").agg(F.first("shingles").alias("shingles"))


def _verified(pairs: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    """The pairs (a, b) whose full sets reach the threshold."""
    left = sets.select(F.col("key").alias("a"), F.col("shingles").alias("sa"))
    right = sets.select(F.col("key").alias("b"), F.col("shingles").alias("sb"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ok = []
            for x, y in zip(b.column("sa").to_pylist(), b.column("sb").to_pylist(), strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                ok.append(both >= threshold * (len(x) + len(y) - both) - 1e-9)
            yield b.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))

    return pairs.join(left, "a").join(right, "b").select("a", "b", "sa", "sb").mapInArrow(run, "a binary, b binary")


def block_links(keys: list[bytes], copies: np.ndarray, sets: list[np.ndarray], side: np.ndarray, threshold: float, bands: np.ndarray, portion: int = 4096) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """Within a pair of blocks: links of each member (weighted by copies) and a spanning forest.

    ``bands`` holds the band hashes of each member in a row; a link needs one in common. ``side`` is 0 or 1; pairs within one side belong to another group unless all are of side 0.
    """
    n = len(keys)
    sizes = np.asarray([len(s) for s in sets], np.int64)
    owner = np.repeat(np.arange(n), sizes)
    flat = np.concatenate(sets) if n else np.zeros(0, np.uint64)
    values, column, times = np.unique(flat, return_inverse=True, return_counts=True)
    shared = times[column] > 1
    column, owner = column[shared], owner[shared]
    renumber = np.cumsum(times > 1) - 1
    column = renumber[column]
    order = np.argsort(column, kind="stable")
    column, owner = column[order], owner[order]
    one = not side.any()
    a, b = (np.arange(n), np.arange(n)) if one else (np.flatnonzero(side == 0), np.flatnonzero(side == 1))
    at = np.zeros(n, np.int64)
    at[a] = np.arange(len(a))
    at_b = np.zeros(n, np.int64)
    at_b[b] = np.arange(len(b))
    both = np.zeros((len(a), len(b)), np.float32)
    width = int(column[-1]) + 1 if len(column) else 0
    for lo in range(0, width, portion):
        i, j = np.searchsorted(column, [lo, lo + portion])
        o, c = owner[i:j], column[i:j] - lo
        left = np.zeros((len(a), portion), np.float32)
        if one:
            left[at[o], c] = 1
            right = left
        else:
            right = np.zeros((len(b), portion), np.float32)
            first = side[o] == 0
            left[at[o[first]], c[first]] = 1
            right[at_b[o[~first]], c[~first]] = 1
        both += left @ right.T
    union = sizes[a][:, None] + sizes[b][None, :] - both
    linked = both >= threshold * union - 1e-9
    meet = np.zeros_like(linked)
    for c in range(bands.shape[1]):
        meet |= bands[a, c][:, None] == bands[b, c][None, :]
    linked &= meet
    if one:
        np.fill_diagonal(linked, False)
    links = np.zeros(n, np.int64)
    links[a] += linked @ copies[b]
    if not one:
        links[b] += linked.T @ copies[a]
    root = list(range(n))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    forest = []
    for x in range(len(a)):
        for y in np.flatnonzero(linked[x]).tolist():
            u, v = find(int(a[x])), find(int(b[y]))
            if u != v:
                root[u] = v
                forest.append((int(a[x]), int(b[y])))
    return links, forest


def _families(members: DataFrame) -> DataFrame:
    """(key, family) of the members (key, hub) of large buckets."""
    joined = components(members.select(F.col("key").alias("u"), F.col("hub").alias("v")))
    vertices = members.select("key").distinct()
    return vertices.join(joined.select(F.col("u").alias("key"), F.col("v").alias("family")), "key", "left").select("key", F.coalesce("family", "key").alias("family"))


def _family_links(families: DataFrame, sets: DataFrame, reps: DataFrame, threshold: float, block: int) -> DataFrame:
    """One row per (key, weighted links) or (key, other) of a spanning forest, from all block pairs."""
    sizes = families.groupBy("family").agg(F.count("*").alias("size"))
    own = families.join(sizes, "family").withColumn("blocks", F.ceil(F.col("size") / block).cast("int")).withColumn("own", F.pmod(F.xxhash64("key"), F.col("blocks")).cast("int"))
    full = own.join(sets, "key").join(reps.select("key", "copies", "bands"), "key")
    tasks = full.select("key", "family", "shingles", "copies", "bands", "own", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    tasks = tasks.select("key", "shingles", "copies", "bands", "family", "own", F.least("own", "other").alias("p"), F.greatest("own", "other").alias("q"))

    def run(group: pa.Table) -> pa.Table:
        group = group.sort_by("key")
        keys = group.column("key").to_pylist()
        sets_ = [np.frombuffer(x, np.uint64) for x in group.column("shingles").to_pylist()]
        p, q = group.column("p")[0].as_py(), group.column("q")[0].as_py()
        side = np.zeros(len(keys), np.int64) if p == q else (group.column("own").to_numpy() == q).astype(np.int64)
        links, forest = block_links(keys, group.column("copies").to_numpy().astype(np.int64), sets_, side, threshold, np.asarray(group.column("bands").to_pylist(), np.int64))
        at = np.flatnonzero(links)
        return pa.table(
            {
                "key": pa.array([keys[i] for i in at] + [keys[x] for x, _ in forest], pa.binary()),
                "other": pa.array([None] * len(at) + [keys[y] for _, y in forest], pa.binary()),
                "links": pa.array(links[at].tolist() + [0] * len(forest), pa.int64()),
            }
        )

    return tasks.groupBy("family", "p", "q").applyInArrow(run, "key binary, other binary, links long")


def join(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", threshold: float = 0.8, recall: float = 0.99999, small: int = 16, block: int = 256) -> DataFrame:
    """Per row of ``docs``: d, h, class_id (least id of its class), n_copies, n_links, class_key, is_first."""
    tame_arrow(docs.sparkSession)
    bands, rows = bands_for(threshold, recall)
    signed = stored(signatures(docs, text, doc_id, bands, rows), "signatures")
    reps = signed.groupBy("key").agg(F.min("d").alias("d"), F.min(F.struct("d", "h")).alias("first"), F.count("*").alias("copies"), F.any_value("n").alias("n"), F.any_value("bands").alias("bands"))
    reps = stored(reps, "representatives")
    slots = reps.where("n > 0").select("key", F.explode("bands").alias("slot"))
    buckets = stored(slots.groupBy("slot").agg(F.count("*").alias("k"), F.min("key").alias("hub")).where("k > 1").select("*", F.col("k").alias("weight")), "band-hashes")
    members = stored(join_hot(slots, buckets, ["slot"], "weight"), "buckets")
    families = stored(_families(members.where(F.col("k") > small)), "families")
    few = members.where(F.col("k") <= small)
    pairs = few.select("slot", F.col("key").alias("a")).join(few.select("slot", F.col("key").alias("b")), "slot").where("a < b").select("a", "b").distinct()
    fam = families.select(F.col("key").alias("a"), F.col("family").alias("fa")), families.select(F.col("key").alias("b"), F.col("family").alias("fb"))
    pairs = pairs.join(fam[0], "a", "left").join(fam[1], "b", "left").where(F.col("fa").isNull() | F.col("fb").isNull() | (F.col("fa") != F.col("fb"))).select("a", "b")
    pairs = stored(pairs, "pairs")
    wanted = stored(pairs.select(F.explode(F.array("a", "b")).alias("key")).unionByName(families.select("key")).distinct().join(reps.select("key", "d"), "key"), "wanted")
    sets = stored(_sets(docs, wanted, text, doc_id), "shingle-sets")
    links = stored(_verified(pairs, sets, threshold), "links")
    inner = stored(_family_links(families, sets, reps, threshold, block), "family-links")
    forest = links.unionByName(inner.where("other is not null").select(F.col("key").alias("a"), F.col("other").alias("b")))
    classes = components(forest.select(F.col("a").alias("u"), F.col("b").alias("v")))
    copies = reps.select("key", "copies")
    ends = links.select(F.col("a").alias("x"), F.col("b").alias("key")).unionByName(links.select(F.col("b").alias("x"), F.col("a").alias("key")))
    weighed = ends.join(copies, "key").select(F.col("x").alias("key"), F.col("copies").alias("links")).unionByName(inner.where("other is null").select("key", "links"))
    counted = weighed.groupBy("key").agg(F.sum("links").alias("links"))
    labelled = reps.join(classes.select(F.col("u").alias("key"), F.col("v").alias("root")), "key", "left").withColumn("root", F.coalesce("root", "key"))
    labelled = stored(labelled.select("key", "first", "copies", "root"), "labelled")
    roots = labelled.groupBy("root").agg(F.min("first").alias("class_first"), F.count("*").alias("members"))
    table = join_hot(labelled, roots, ["root"], "members").join(counted, "key", "left").select("key", "root", "class_first", "copies", F.col("copies").alias("weight"), (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("links"))
    out = join_hot(signed.select("d", "h", "key"), stored(table, "classes"), ["key"], "weight")
    return out.select("d", "h", F.col("class_first.d").alias("class_id"), F.col("copies").alias("n_copies"), F.col("links").alias("n_links"), F.col("root").alias("class_key"), (F.struct("d", "h") == F.col("class_first")).alias("is_first"))


def drop_near_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", **options) -> DataFrame:
    """One row of each class (the one with the least id), with the columns of ``docs``."""
    found = join(docs, text, doc_id, **options).where("is_first")
    d, h, c, own = fresh(docs.columns, "first_id", "first_hash", "first_class", "own_hash")
    firsts = found.select(F.col("d").alias(d), F.col("h").alias(h), F.col("class_key").alias(c)).dropDuplicates([c])
    keyed = docs.withColumn(own, F.xxhash64(F.col(f"`{text}`")))
    kept = keyed.join(firsts, F.col(f"`{doc_id}`").cast("long").eqNullSafe(F.col(d)) & (F.col(own) == F.col(h)))
    return kept.dropDuplicates([c]).select(*[F.col(f"`{x}`") for x in docs.columns])


def op2_near_duplicates(spark, sf_dir: str) -> DataFrame:
    """doc_id, class_id, n_copies and n_links of every document."""
    from cubegrid.llm.common import table

    out = join(table(spark, sf_dir, "documents"))
    return out.select(F.col("d").alias("doc_id"), "class_id", "n_copies", "n_links")
