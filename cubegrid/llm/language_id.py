"""Language identification: multinomial naive Bayes over hashed character n-grams.

Training counts hashed 1-, 2- and 3-grams of characters per language in an Arrow function (sparse
partial counts, summed by Spark); the log-probability matrix (languages x buckets, a fixed size)
is broadcast, and texts are scored in numpy as sparse gathers from it.

Defined results: null text, or a text without a letter, gives ``und`` with score 0. Rows with a
null id count as id "" for the fold. Rows with null lang are never learnt from. An empty training
set gives ``und`` for every text. Repeated rows are each scored. Only the named columns are used,
so further columns with any names do no harm.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubegrid.llm.common import fresh, id_crc, slices, starts_of, tame_arrow, texts

BUCKETS = 1 << 16
ORDERS = (1, 2, 3)
#: A text is cut into pieces of so many characters, so that memory does not grow with its length.
PIECE = 1 << 18
_SALT = {1: 0x9E3779B1, 2: 0x85EBCA77, 3: 0xC2B2AE3D, 4: 0x27D4EB2F, 5: 0x165667B1}


@dataclass
class LanguageModel:
    langs: list[str]
    logp: np.ndarray  # languages x buckets, float32
    prior: np.ndarray


def _pieces(rows: list[str | None]) -> Iterator[tuple[list[int], list[str]]]:
    """Blocks of (row number, piece) with about PIECE characters; pieces of one text overlap."""
    idx: list[int] = []
    out: list[str] = []
    size = 0
    for i, text in enumerate(rows):
        if text is None:
            continue
        text = text.lower()
        for lo in range(0, max(1, len(text)), PIECE):
            # two characters of context keep the n-grams across a cut, none is counted twice
            piece = f" {text[:PIECE]}" if lo == 0 else text[lo - 2 : lo + PIECE]
            idx.append(i if lo == 0 else -i - 1)
            out.append(piece)
            size += len(piece)
            if size >= PIECE:
                yield idx, out
                idx, out, size = [], [], 0
    if out:
        yield idx, out


def _grams(idx: list[int], pieces: list[str], buckets: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row of each n-gram, its bucket), order by order, over a block of pieces."""
    joined = "".join(pieces)
    codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32).copy()
    codes[((codes < 97) | ((codes > 122) & (codes < 128)))] = 32  # ASCII non-letters
    lens = np.fromiter(map(len, pieces), np.int64, len(pieces))
    begin = starts_of(lens)[:-1]
    order = np.asarray(idx)
    cont = order < 0  # a continued text: its first two characters are context only
    rows = np.where(cont, -order - 1, order)
    owner = np.repeat(np.arange(len(pieces)), lens)
    at = np.arange(len(codes)) - np.repeat(begin, lens)
    size = np.repeat(lens, lens)
    begun = np.repeat(np.where(cont, 2, 0), lens)
    shift = np.uint32(32 - int(buckets).bit_length() + 1)
    for n in ORDERS:
        m = len(codes) - n + 1
        if m <= 0:
            continue
        h = np.full(m, _SALT[n], np.uint32)
        for k in range(n):
            h ^= codes[k : k + m]
            h *= np.uint32(0x01000193)
            h ^= h >> np.uint32(15)
        h *= np.uint32(0x9E3779B1)
        ok = (at[:m] + n <= size[:m]) & (at[:m] + n - 1 >= begun[:m])
        if n == 1:
            ok &= codes[:m] != 32
        elif n == 2:
            ok &= (codes[:m] != 32) | (codes[1 : m + 1] != 32)
        else:
            ok &= codes[1 : m + 1] != 32
        yield rows[owner[:m][ok]], (h[ok] >> shift).astype(np.int64)


def count_grams(docs: DataFrame, text: str, lang: str, buckets: int = BUCKETS) -> DataFrame:
    """(lang, bucket, n) over the rows given; partial sums per partition, then a Spark aggregation."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[str, np.ndarray] = {}
        for part in slices(batches, "text"):
            langs = part.column("lang").to_pylist()
            names = sorted(set(langs))
            code = np.asarray([names.index(x) for x in langs])
            sums = np.zeros(len(names) * buckets, np.int64)
            for idx, pieces in _pieces(texts(part)):
                for rows, bucket in _grams(idx, pieces, buckets):
                    sums += np.bincount(code[rows] * buckets + bucket, minlength=len(sums))
            for k, name in enumerate(names):
                own = sums[k * buckets : (k + 1) * buckets]
                total[name] = total[name] + own if name in total else own.copy()
        for name, sums in total.items():
            at = np.flatnonzero(sums)
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(at), pa.string()), pa.array(at), pa.array(sums[at])], names=["lang", "bucket", "n"])

    narrow = docs.select(F.col(text).alias("text"), F.col(lang).alias("lang"))
    return narrow.mapInArrow(run, "lang string, bucket long, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))


def fit(docs: DataFrame, where: Column, text: str = "text", lang: str = "lang", doc_id: str = "doc_id", docs_per_lang: int = 8000, buckets: int = BUCKETS, smooth: float = 0.5) -> LanguageModel:
    """Fit on the labelled rows that ``where`` admits, about ``docs_per_lang`` of each language at most.

    The bound is on the fit alone: languages with more rows are thinned by a hash of the id. What
    reaches the driver is languages x buckets numbers, whatever the size of the corpus.
    """
    tame_arrow(docs.sparkSession)
    rows = docs.where(where & F.col(lang).isNotNull() & F.col(text).isNotNull())
    sizes = {r[0]: r[1] for r in rows.groupBy(lang).count().collect()}
    langs = sorted(sizes)
    if not langs:
        return LanguageModel([], np.zeros((0, buckets), np.float32), np.zeros(0))
    share = F.create_map(*[F.lit(x) for k in langs for x in (k, min(1.0, docs_per_lang / sizes[k]))])
    dice = F.pmod(F.xxhash64(F.col(doc_id).cast("string"), F.lit(11)), F.lit(1 << 20)) / F.lit(float(1 << 20))
    counted = count_grams(rows.where(dice < F.element_at(share, F.col(lang))), text, lang, buckets).toPandas()
    sums = np.zeros((len(langs), buckets))
    sums[np.searchsorted(langs, counted["lang"].to_numpy(str)), counted["bucket"].to_numpy()] = counted["n"].to_numpy()
    logp = np.log(sums + smooth) - np.log(sums.sum(1, keepdims=True) + smooth * buckets)
    n = np.asarray([sizes[k] for k in langs], float)  # of all rows, not of the thinned ones
    return LanguageModel(langs, logp.astype(np.float32), np.log(n / n.sum()))


def predict(docs: DataFrame, model: LanguageModel, text: str = "text", keep: tuple[str, ...] = ("doc_id",), buckets: int = BUCKETS, names: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """The columns in ``keep`` plus the language and its score, one row per row of ``docs``; no shuffle."""
    spark = docs.sparkSession
    tame_arrow(spark)
    shared = spark.sparkContext.broadcast(model)
    own = fresh(list(keep), "text")[0]
    narrow = docs.select(*[F.col(f"`{k}`") for k in keep], F.col(text).alias(own))
    schema = narrow.drop(own).schema.add(names[0], "string").add(names[1], "double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for part in slices(batches, own):
            rows = texts(part, own)
            langs, score = score_texts(rows, m, buckets)
            held = [part.column(i) for i in range(len(keep))]
            yield pa.RecordBatch.from_arrays([*held, pa.array(langs, pa.string()), pa.array(score)], names=[*keep, *names])

    return narrow.mapInArrow(run, schema)


def score_texts(rows: list[str | None], m: LanguageModel, buckets: int = BUCKETS) -> tuple[list[str], np.ndarray]:
    n_lang = len(m.langs)
    ll = np.zeros((n_lang, len(rows)))
    if n_lang:
        for idx, pieces in _pieces(rows):
            for at, bucket in _grams(idx, pieces, buckets):
                for k in range(n_lang):
                    ll[k] += np.bincount(at, m.logp[k][bucket], len(rows))
    langs: list[str] = ["und"] * len(rows)
    score = np.zeros(len(rows))
    if n_lang:
        # n-grams overlap, so the orders count as one piece of evidence together
        post = ll / len(ORDERS) + m.prior[:, None]
        best = post.argmax(0)
        post = np.exp(post - post.max(0))
        p = post.max(0) / post.sum(0)
        for i, t in enumerate(rows):
            if t is not None and any(map(str.isalpha, t)):
                langs[i], score[i] = m.langs[best[i]], p[i]
    return langs, score


def is_held_out(doc_id: Column) -> Column:
    return id_crc(doc_id) % 5 == 0


def identify(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), **fit_options) -> DataFrame:
    """Fit on the rows outside the held-out fold and predict every row."""
    model = fit(docs, ~is_held_out(F.col("doc_id")), **fit_options)
    return predict(docs, model, keep=keep)


def op10_language_id(spark, sf_dir: str) -> DataFrame:
    """doc_id, held_out, lang_pred, score of every document."""
    from cubegrid.llm.common import table

    out = identify(table(spark, sf_dir, "documents"))
    return out.select("doc_id", is_held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
