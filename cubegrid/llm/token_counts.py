"""Token counts: batch encoding in Arrow functions that return lengths only.

Texts are cut at ASCII white space, across which this tokenizer's pre-tokens never reach (its
pre-tokenizer drops white space, its normaliser cannot compose across it and no special token
holds any), so the count of a text is the sum over its chunks. Each distinct chunk of a slice is
encoded once, in batches balanced by bytes, and remembered in a bounded table. A chunk is never
cut, so the sum is exact for texts of any length; a text without white space is one chunk. Another
tokenizer is first tried on probes, and gets whole texts where it does not count chunk by chunk.

Defined results: null counts as the empty text (0 tokens). Repeated rows are each counted; an
empty table gives no row; further columns do no harm.
"""

from __future__ import annotations

import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubegrid.llm.common import fresh, slices, tame_arrow


#: Texts on which a tokenizer must count chunk by chunk as it does as a whole.
_PROBES = ("two words", "a  b\t\tc", "line one.\nLine two!\r\n\r\n  indented", " 1 234 , 5", "\u00e9t\u00e9 \u4e2d\u6587 \u00fc")
#: Longer chunks are not remembered, so that memory is bounded in bytes.
_LONG_CHUNK = 256


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class ChunkCounter:
    """Token counts of white-space-free chunks by the tokenizer itself, remembered up to a limit."""

    def __init__(self, path: str, remember: int = 400_000, batch_bytes: int = 1 << 18):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.no_truncation()
        self.tok.no_padding()
        self.known: dict[bytes, int] = {}
        self.remember, self.batch_bytes = remember, batch_bytes
        # a tokenizer that counts white space, or joins across it, gets whole texts
        one = lambda t: len(self.tok.encode(t, add_special_tokens=False))
        self.cuts = all(one(t) == sum(map(one, t.split())) for t in _PROBES)

    def _learn(self, chunks: list[bytes]) -> None:
        batch: list[str] = []
        keys: list[bytes] = []
        size = 0
        for c in chunks:
            keys.append(c)
            batch.append(c.decode("utf-8", "surrogatepass"))
            size += len(c)
            if size >= self.batch_bytes:
                self._encode(keys, batch)
                batch, keys, size = [], [], 0
        if batch:
            self._encode(keys, batch)

    def _encode(self, keys: list[bytes], batch: list[str]) -> None:
        self.known.update(zip(keys, map(len, self.tok.encode_batch_fast(batch, add_special_tokens=False)), strict=True))

    def count(self, rows: list[bytes]) -> np.ndarray:
        # bytes.split cuts at ASCII white space only
        parts = [r.split() for r in rows] if self.cuts else [[r] for r in rows]
        seen = set().union(*parts)
        new = [c for c in seen if c not in self.known]
        if len(self.known) + len(new) > self.remember:
            self.known.clear()
            new = list(seen)
        self._learn(new)
        get = self.known.__getitem__
        out = np.fromiter((sum(map(get, p)) for p in parts), np.int64, len(parts))
        for c in new:
            if len(c) > _LONG_CHUNK:
                del self.known[c]
        return out


def count_tokens(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",), path: str | None = None) -> DataFrame:
    """``keep`` plus n_bytes and n_tokens; nothing but lengths leaves the Arrow function."""
    tame_arrow(docs.sparkSession)
    where = path or tokenizer_path()
    own = fresh(list(keep), "text")[0]
    narrow = docs.select(*[F.col(f"`{k}`") for k in keep], F.coalesce(F.col(text), F.lit("")).cast("binary").alias(own))
    schema = narrow.drop(own).schema.add("n_bytes", "long").add("n_tokens", "long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = None
        for part in slices(batches, own, 2 << 20):
            counter = counter or ChunkCounter(where)
            rows = part.column(own).to_pylist()
            held = [part.column(i) for i in range(len(keep))]
            yield pa.RecordBatch.from_arrays([*held, pa.array(np.fromiter(map(len, rows), np.int64, len(rows))), pa.array(counter.count(rows))], names=[*keep, "n_bytes", "n_tokens"])

    return narrow.mapInArrow(run, schema)


def op5_token_counts(spark, sf_dir: str, limit: int = 2048) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit of every document."""
    from cubegrid.llm.common import table

    out = count_tokens(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
