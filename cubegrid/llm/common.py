"""Helpers shared by the operators of this subpackage: text batches, word rules, shared storage."""

from __future__ import annotations

import re
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cubegrid.fs import shared_root

#: Words of the decontamination and shingle rules: maximal runs of what is not ASCII punctuation,
#: white space or control, after A-Z are lower-cased (other letters stay as they are).
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_LOWER = {c: c + 32 for c in range(65, 91)}


def words_of(text: str) -> list[str]:
    """Lower-case A-Z and split into words."""
    lowered = text.lower() if text.isascii() else text.translate(_LOWER)
    return WORD.findall(lowered)


#: Bytes of UTF-8 by the same rule: A-Z lower-cased, what parts words a space; other letters are no ASCII bytes.
_WORD_BYTES = bytes(c if c > 127 else ord(chr(c).lower()) if chr(c).isalnum() else 32 for c in range(256))


def word_bytes(text: bytes) -> list[bytes]:
    """The words of ``words_of`` in UTF-8, from a text in UTF-8; several times as fast."""
    return text.translate(_WORD_BYTES).split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tame_arrow(spark: SparkSession, rows: int = 1000) -> None:
    """Keep Arrow batches small for wide text rows; a runtime setting, only ever lowered."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key))
    if now <= 0 or now > rows:
        spark.conf.set(key, str(rows))


def id_crc(col: Column) -> Column:
    """crc32 of an id written as text; a null id counts as the empty text."""
    return F.crc32(F.coalesce(col.cast("string"), F.lit("")).cast("binary"))


def shared_path(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read back: cuts lineage and survives lost executors."""
    path = shared_path(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def fresh(taken: list[str], *names: str) -> list[str]:
    """Names like the given ones that clash with no column in ``taken``, whatever the case."""
    lower, out = {c.lower() for c in taken}, []
    for n in names:
        while n.lower() in lower:
            n += "_"
        lower.add(n.lower())
        out.append(n)
    return out


#: Keys that are met by broadcast in ``join_hot``: the heaviest ones, so that none left is above this share.
HOT_KEYS = 1000


def join_hot(rows: DataFrame, classes: DataFrame, keys: list[str], weight: str, how: str = "inner") -> DataFrame:
    """Join rows with a table of one row per key, when one key may bear a large share of the rows.

    The ``HOT_KEYS`` keys of greatest ``weight`` (rows per key, a column of ``classes`` that is dropped) are
    broadcast; as many rows, so of bounded size. Every other key bears less than that share of all rows and is
    shuffled; rows of hot keys are dealt evenly in the same shuffle. Keys are never null in ``classes``.
    """
    others = [c for c in classes.columns if c not in keys and c != weight]
    key_of = lambda frame: [F.col(k).alias(f"__k_{k}") for k in keys]  # noqa: E731, ARG005
    hot = classes.orderBy(F.desc(weight), *keys).limit(HOT_KEYS).select(*key_of(classes), *[F.col(c).alias(f"__hot_{c}") for c in others], F.lit(True).alias("__hot"))
    # always 0, but no literal: the optimizer would fold that into a filter and deal rows by the keys alone
    nought = F.pmod(F.xxhash64(*[F.col(k) for k in keys]), F.lit(1)).cast("int")
    cold = classes.select(*key_of(classes), *[F.col(c).alias(f"__cold_{c}") for c in others], nought.alias("__deal0"), F.lit(True).alias("__cold"))
    met = rows.join(F.broadcast(hot), [F.col(k) == F.col(f"__k_{k}") for k in keys], "left").drop(*[f"__k_{k}" for k in keys])
    met = met.withColumn("__deal", F.when(F.col("__hot"), 1 + F.pmod(F.xxhash64(*[F.col(f"`{c}`") for c in rows.columns]), F.lit(1 << 20))).otherwise(0).cast("int"))
    met = met.join(cold, [*[F.col(k) == F.col(f"__k_{k}") for k in keys], F.col("__deal") == F.col("__deal0")], "left")
    if how == "inner":
        met = met.where(F.col("__hot") | F.col("__cold"))
    return met.select(*[F.col(f"`{c}`") for c in rows.columns], *[F.when(F.col("__hot"), F.col(f"__hot_{c}")).otherwise(F.col(f"__cold_{c}")).alias(c) for c in others])


def slices(batches: Iterator[pa.RecordBatch], col: str, max_bytes: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Cut record batches so that the texts of each slice hold about ``max_bytes`` (one row at least)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        size = pc.fill_null(pc.binary_length(batch.column(col)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        part = np.cumsum(size) // max_bytes
        cuts = np.flatnonzero(np.diff(part)) + 1
        for lo, hi in zip([0, *cuts], [*cuts, batch.num_rows], strict=True):
            yield batch.slice(lo, hi - lo)


def texts(batch: pa.RecordBatch, col: str = "text") -> list[str | None]:
    return batch.column(col).to_pylist()


class WordIds(dict):
    """64-bit hash of each word, computed once; cleared when large so that memory stays bounded. Very long
    words are not kept."""

    LIMIT, LONGEST = 300_000, 64

    def __missing__(self, word: str) -> int:
        from xxhash import xxh3_64_intdigest

        value = xxh3_64_intdigest(word.encode("utf-8", "surrogatepass"))
        if len(word) <= self.LONGEST:
            if len(self) >= self.LIMIT:
                self.clear()
            self[word] = value
        return value

    def array(self, words: list[str]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads the bits of uint64 values (in place)."""
    x ^= x >> np.uint64(31)
    x *= np.uint64(0x7FB5D329728EA185)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x81DADEF4BC2DD44D)
    x ^= x >> np.uint64(33)
    return x


def starts_of(lengths: np.ndarray) -> np.ndarray:
    out = np.zeros(len(lengths) + 1, np.int64)
    np.cumsum(lengths, out=out[1:])
    return out
