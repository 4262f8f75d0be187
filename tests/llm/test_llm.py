"""The ten operators and the pipeline against brute force, round trips and held-out accuracy, and odd input."""

from __future__ import annotations

import base64
import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from conftest import SF001
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from cubegrid.llm import decontaminate, gif, language_id, line_dedup, mixing, near_dup, quality, registry, substring_dedup, token_counts, warc
from cubegrid.llm.common import WordIds, shared_path, word_bytes, words_of
from cubegrid.llm.rindex import RunLengthIndex

WORDS = "the and of in that river stone light paper green house under seven north again".split()


def prose(rng, n):
    return " ".join(rng.choice(WORDS) + str(rng.randrange(60)) for _ in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empties, repeated rows, copies, near copies, long text, and columns with clashing names."""
    rng = random.Random(2)
    lines = [prose(rng, 9) for _ in range(12)]
    long = " ".join(prose(rng, 40) for _ in range(150))
    near = prose(rng, 120).split()
    texts = [
        (0, "\n".join(lines[:6])), (1, "\n".join([lines[9], *lines[2:5], "", lines[10]])), (2, None), (3, ""), (4, "   \n \n"),
        (5, "!!! 123"), (6, "one two"), (7, "one two"), (8, "one two three"), (None, "\n".join(lines[:3])), (None, None),
        (9, long), (10, long[5:] + " tail"), (11, " ".join(near)), (12, " ".join([*near[:60], "changed", *near[61:]])), (13, " ".join(near)),
        (14, "ÄÖ straße ÑANDÚ çedilla <|endoftext|> it's"), (15, "x" * 200), (15, "x" * 200), (16, "\n".join(lines[6:9] * 2)), (17, "\0 zero \0 bytes " * 6),
    ]
    rows = [(i, t, "en" if k % 2 else None, None if k % 5 == 0 else f"s{k % 3}", len(t) if t else 0, k, "z", k, k, k, "k") for k, (i, t) in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, d long, h string, key long, n long, score long, gone string").repartition(3).cache()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF001}/documents.parquet")


def collected(docs):
    return [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]


# ---- language, quality, tokens ------------------------------------------------------------------------


def test_language_accuracy_and_odd(spark, docs, odd):
    model = language_id.fit(docs, ~language_id.is_held_out(F.col("doc_id")))
    got = language_id.predict(docs, model, keep=("doc_id", "lang")).where(language_id.is_held_out(F.col("doc_id")))
    rows = got.collect()
    assert rows and sum(r.lang == r.lang_pred for r in rows) >= 0.95 * len(rows)
    out = language_id.predict(odd, model, keep=tuple(odd.columns), names=("l", "p")).collect()
    assert len(out) == odd.count()
    for r in out:
        assert (r.l == "und") == (not r.text or not re.search(r"[^\W\d_]", r.text)) and 0 <= r.p <= 1
    empty = language_id.identify(docs.limit(0))
    assert empty.count() == 0
    assert {r.lang_pred for r in language_id.predict(odd, language_id.fit(odd.limit(0), F.lit(True))).collect()} == {"und"}


def test_language_pieces_do_not_change_scores(docs, monkeypatch):
    model = language_id.fit(docs, F.lit(True))
    rows = [t for _, t in collected(docs)][:20]
    whole = language_id.score_texts(rows, model)
    monkeypatch.setattr(language_id, "PIECE", 97)
    cut = language_id.score_texts(rows, model)
    assert whole[0] == cut[0] and np.allclose(whole[1], cut[1])


def hash_of_gram(gram, buckets):
    """The bucket of an n-gram in plain integers."""
    h = {1: 0x9E3779B1, 2: 0x85EBCA77, 3: 0xC2B2AE3D}[len(gram)]
    for c in gram:
        h = (h ^ ord(c)) * 0x01000193 % 2**32
        h ^= h >> 15
    return (h * 0x9E3779B1 % 2**32) // (2**32 // buckets)


def grams_of(text):
    text = " " + "".join(" " if ord(c) < 128 and not "a" <= c <= "z" else c for c in text.lower())
    out = [c for c in text if c != " "]
    out += [text[i : i + 2] for i in range(len(text) - 1) if text[i : i + 2] != "  "]
    return out + [text[i : i + 3] for i in range(len(text) - 2) if text[i + 1] != " "]


def test_language_equals_dense_naive_bayes(spark):
    """Counts, smoothed log-probabilities, priors and posteriors worked out gram by gram in plain Python."""
    rows = [(k, prose(random.Random(k), 12 + k) + (" über ñu" if k % 3 == 0 else " the end"), "de" if k % 3 == 0 else "en") for k in range(20)]
    rows += [(20, "", "en"), (21, None, "de"), (22, "no language", None), (23, "ab 1", "en")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3)
    buckets = 1 << 10
    model = language_id.fit(frame, F.lit(True), buckets=buckets)
    learnt = [(t, lang) for _, t, lang in rows if t is not None and lang is not None]
    counts = {k: Counter(hash_of_gram(g, buckets) for t, lang in learnt if lang == k for g in grams_of(t)) for k in ("de", "en")}
    logp = {k: [np.log((c[b] + 0.5) / (sum(c.values()) + 0.5 * buckets)) for b in range(buckets)] for k, c in counts.items()}
    prior = {k: np.log(sum(lang == k for _, lang in learnt) / len(learnt)) for k in counts}
    assert model.langs == ["de", "en"]
    assert np.allclose(model.logp, [logp["de"], logp["en"]], atol=1e-5) and np.allclose(model.prior, [prior["de"], prior["en"]])
    for r in language_id.predict(frame, model, buckets=buckets).join(frame.select("doc_id", "text"), "doc_id").collect():
        if r.text is None or not any(map(str.isalpha, r.text)):
            assert (r.lang_pred, r.score) == ("und", 0.0)
            continue
        post = {k: sum(logp[k][hash_of_gram(g, buckets)] for g in grams_of(r.text)) / 3 + prior[k] for k in counts}
        best = max(sorted(post), key=post.get)
        assert r.lang_pred == best and abs(r.score - 1 / sum(np.exp(x - post[best]) for x in post.values())) < 1e-3


def test_quality_accuracy_and_odd(spark, docs, odd):
    labels = spark.read.parquet(f"{SF001}/labels.parquet")
    model = quality.fit(docs, labels, ~quality.is_held_out(F.col("doc_id")))
    got = quality.predict(docs, model).join(labels, "doc_id").where(quality.is_held_out(F.col("doc_id"))).collect()
    assert sum(r.predicted == r.quality for r in got) >= 0.9 * len(got)
    out = quality.predict(odd, model, keep=("doc_id", "key")).collect()
    assert len(out) == odd.count() and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in out)
    none = quality.fit(docs, labels.limit(0), F.lit(True))
    assert {r.score for r in quality.predict(odd, none).collect()} == {0.5}


def test_dual_coordinate_descent_separates():
    rng = np.random.default_rng(0)
    rows = [np.unique(rng.integers(0, 200, 20)).astype(np.int32) + (300 if k % 2 else 0) for k in range(60)]
    y = np.asarray([1.0 if k % 2 else -1.0 for k in range(60)])
    m = quality.fit_rows_model(rows, y)
    assert all((quality.score_one(r, m) > 0.5) == (k > 0) for r, k in zip(rows, y, strict=True))


def test_quality_model_is_the_dual_optimum():
    """Ratios from dense counts; the dual problem's optimality conditions and duality gap in dense arithmetic."""
    rng = np.random.default_rng(3)
    rows = [np.unique(rng.integers(0, 40, 12) + (8 if k % 2 else 0)).astype(np.int32) for k in range(50)]
    y = np.asarray([1.0 if (k % 2) ^ (k % 11 == 0) else -1.0 for k in range(50)])
    ratio = quality.log_count_ratio(rows, y)
    dense = np.zeros((50, 1 << quality.BITS), np.float32)
    for k, r in enumerate(rows):
        dense[k, r] = 1
    good, bad = 1 + dense[y > 0].sum(0, dtype=float), 1 + dense[y < 0].sum(0, dtype=float)
    assert np.allclose(ratio, np.log(good / good.sum()) - np.log(bad / bad.sum()))
    dense = dense[:, :64]
    x = dense * ratio[:64]
    x /= np.sqrt((x * x).sum(1, keepdims=True))
    w, bias = quality.dual_coordinate_descent(rows, [ratio[r] / np.sqrt(ratio[r] @ ratio[r]) for r in rows], y, c=1.0, epochs=3000)
    assert not w[64:].any()
    full, own = np.hstack([x, np.ones((50, 1))]), np.append(w[:64], bias)
    primal = own @ own / 2 + np.maximum(0, 1 - y * (full @ own)).sum()
    # the best dual value by plain projected gradient on the same box
    kernel = (full * y[:, None]) @ (full * y[:, None]).T
    alpha, step = np.zeros(50), 1 / np.linalg.eigvalsh(kernel)[-1]
    for _ in range(60000):
        alpha = np.clip(alpha - step * (kernel @ alpha - 1), 0, 1)
    dual = alpha.sum() - alpha @ kernel @ alpha / 2
    assert dual - 1e-6 <= primal <= dual * 1.005
    assert np.allclose(own, (alpha * y) @ full, atol=0.05)


def test_token_counts_equal_the_tokenizer(odd, docs):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(token_counts.tokenizer_path())
    for part in (odd, docs):
        want = Counter((i, len((t or "").encode()), len(tok.encode(t or "", add_special_tokens=False).ids)) for i, t in collected(part))
        assert Counter((r.doc_id, r.n_bytes, r.n_tokens) for r in token_counts.count_tokens(part).collect()) == want
    counter = token_counts.ChunkCounter(token_counts.tokenizer_path(), remember=50, batch_bytes=64)  # tables that overflow
    rows = [(t or "").encode() for _, t in collected(docs)][:40]
    assert counter.count(rows).tolist() == [len(tok.encode(r.decode(), add_special_tokens=False).ids) for r in rows]


# ---- GIF ------------------------------------------------------------------------------------------------


@settings(max_examples=60, deadline=None)
@given(bits=st.integers(2, 8), data=st.binary(max_size=3000), repeat=st.integers(1, 30))
def test_lzw_round_trip(bits, data, repeat):
    data = bytes(b & ((1 << bits) - 1) for b in data * repeat)
    assert gif.lzw_decode(gif.lzw_encode(data, bits), bits, len(data)).tobytes() == data


def test_lzw_long_tables():
    rng = random.Random(1)
    for a in (1, 3, 256):
        data = bytes(rng.randrange(a) for _ in range(70000))
        assert gif.lzw_decode(gif.lzw_encode(data), 8, len(data)).tobytes() == data
    # a stream that never clears a full table again
    codes = [256, *[c for c in data[:6000]], 257]
    widths = [9, *[int(w) for w in gif._WIDTHS[8]], *[12] * 6000]
    bits = "".join(format(c, f"0{w}b")[::-1] for c, w in zip(codes, widths, strict=False))
    stream = bytes(int(bits[i : i + 8].ljust(8, "0")[::-1], 2) for i in range(0, len(bits), 8))
    assert gif.lzw_decode(stream, 8, 6000).tobytes() == data[:6000]
    assert gif.lzw_decode(stream[:300], 8, 6000).tobytes() == data[: len(gif.lzw_decode(stream[:300], 8, 6000))]


def test_gif_disposal_transparency_interlace():
    palette = np.asarray([[0, 0, 0], [255, 0, 0], [0, 255, 0], [0, 0, 255]], np.uint8)
    full = lambda v, r=4, c=4: np.full((r, c), v, np.uint8)
    frames = [
        gif.Frame(0, 0, full(1), 10, 1),
        gif.Frame(1, 1, full(2, 2, 2), 20, 2),  # cleared after it is shown
        gif.Frame(0, 0, np.asarray([[3, 0], [0, 3]], np.uint8), 30, 3, 0),  # transparent, put back afterwards
        gif.Frame(2, 2, full(1, 1, 1), 40, 1, palette=np.asarray([[9, 9, 9], [7, 7, 7]], np.uint8)),
    ]
    got = [(f, f.canvas.copy()) for f in gif.decode(gif.encode(4, 4, frames, palette))]
    assert [f.delay for f, _ in got] == [10, 20, 30, 40]
    a, b, c, d = (x for _, x in got)
    assert (a[..., 0] == 255).all() and tuple(b[1, 1]) == (0, 255, 0, 255) and tuple(b[0, 0]) == (255, 0, 0, 255)
    assert tuple(c[1, 1]) == (0, 0, 255, 255) and tuple(c[0, 1]) == (255, 0, 0, 255) and tuple(c[1, 2]) == (0, 0, 0, 0)
    assert tuple(d[0, 0]) == (255, 0, 0, 255) and tuple(d[2, 2]) == (7, 7, 7, 255)
    # rows stored in interlaced order
    rows = np.repeat(np.arange(8, dtype=np.uint8)[:, None] % 4, 2, axis=1)
    order = [0, 4, 2, 6, 1, 3, 5, 7]
    data = bytearray(gif.encode(2, 8, [gif.Frame(0, 0, rows[order])], palette))
    at = data.index(b"\x2c", 13 + 12)
    data[at + 9] |= 0x40
    assert (next(gif.decode(bytes(data))).indices == rows).all()
    assert gif.histogram(a)[0].tolist() == [0] * 7 + [16]
    assert list(gif.decode(b"")) == [] and list(gif.decode(b"GIF89a")) == [] and list(gif.decode(bytes(data[:40]))) == []


def test_gif_columns(odd):
    media = gif.encode_texts(odd, keep=("doc_id", "key"))
    for r in gif.digest_media(media, keep=("doc_id", "key", "n_bytes")).join(odd.select("key", "text"), "key").collect():
        p = gif.padded((r.text or "").encode())
        assert (r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))
        assert len(p) >= 64 and len(p) % 64 == 0
        rows = [len(p[i : i + gif.COLUMNS * gif.ROWS]) // gif.COLUMNS for i in range(0, len(p), gif.COLUMNS * gif.ROWS)]
        assert [(f.frame, f.start_ms, f.delay_ms, f.width, f.height) for f in r.frames] == [(k, 100 * k, 100, 64, n) for k, n in enumerate(rows)]
        assert r.frames[0].histogram == 3 * [sum(x >> 5 == b for x in p[: gif.COLUMNS * gif.ROWS]) for b in range(8)]
        assert r.feature == ",".join(str(sum(x >> 4 == b for x in p)) for b in range(16))
    frames = gif.decode_frames(media, keep=("key",)).collect()
    assert len(frames) >= odd.count() and all(sum(f.histogram) == 3 * 64 * f.height or f.frame for f in frames)


# ---- WARC -------------------------------------------------------------------------------------------------


def test_warc_round_trip(spark):
    rows = [(k, f"http://h/{k}\r\nX: y", f"<p>{k % 7}</p>" * (k % 5)) for k in range(60)] + [(7, "u", "<p>0</p>"), (59, None, "<p>3</p>" * 4), (None, "n", "<p>3</p>" * 4), (None, None, None), (5, "same", "q"), (5, "same", "q")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("payload", F.lit(1)).withColumn("sha1", F.lit("x"))
    files = []
    for _ in range(2):
        path = shared_path(spark, "warc-test")
        manifest = warc.write(pages, path, shard_bytes=6000, roll_bytes=1500)
        files.append(sorted((r.path.rsplit("/", 1)[1], r.records, r.bytes, r.sha256) for r in manifest.collect()))
        for r in manifest.collect():
            assert hashlib.sha256(open(r.path.removeprefix("file://"), "rb").read()).hexdigest() == r.sha256
    assert files[0] == files[1] and len(files[0]) > 3 and sum(f[1] for f in files[0]) == len(rows)
    got = warc.with_digests(warc.read(manifest)).collect()
    groups = defaultdict(list)
    for p, _, h in rows:
        groups[(h or "").encode()].append(p)
    want = Counter()
    for payload, ids in groups.items():
        known = [p for p in ids if p is not None]
        top, first = max(known, default=None), True
        for p in ids:
            response = top is None or (p == top and first)
            first = first and not (p == top and top is not None)
            want[(p, len(payload), base64.b32encode(hashlib.sha1(payload).digest()).decode(), "response" if response else "revisit", None if response else top)] += 1
    assert Counter((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in got) == want
    assert all("\n" not in (r.url or "") for r in got) and len({r.record_id for r in got if r.page_id is not None}) == sum(r.page_id is not None for r in got)
    assert warc.read(warc.write(pages.limit(0), shared_path(spark, "warc-none"))).count() == 0


def test_warc_shards_of_skewed_ids(spark):
    """Far-off ids, one id and no id on very many pages: every shard stays near its size, in order of its keys."""
    big = 2**63 - 1
    rows = [(k, None, f"{k}" * 9) for k in range(400)] + [(-big - 1, "lowest", "a"), (big, "highest", "b"), (big - 7, None, "c")]
    rows += [(250, None, f"one id {k}") for k in range(1500)] + [(None, None, f"no id {k}") for k in range(1500)] + [(251, None, "same") for _ in range(1500)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(5)
    manifest = warc.write(pages, shared_path(spark, "warc-skew"), shard_bytes=60_000)
    per = Counter()
    for r in manifest.collect():
        per[r.shard] += r.records
    # about 430 bytes a record; the group of equal records is whole
    assert sum(per.values()) == len(rows) and len(per) > 20 and sum(n > 200 for n in per.values()) == 1 and max(per.values()) < 1700
    got = warc.with_digests(warc.read(manifest)).collect()
    assert Counter(r.page_id for r in got) == Counter(r[0] for r in rows)
    assert sum(r.record_type == "revisit" for r in got) == 1499
    order = lambda r: (r.page_id is not None, r.page_id or 0)
    spans = [(min(map(order, g)), max(map(order, g))) for _, g in sorted(by(got, lambda r: r.path.rsplit("/", 1)[1][:11]).items())]
    assert all(a[1] <= b[0] for a, b in zip(spans, spans[1:], strict=False))


def by(rows, key):
    out = defaultdict(list)
    for r in rows:
        out[key(r)].append(r)
    return out


def test_warc_query(spark):
    assert registry.QUERIES["op3_warc"](spark, SF001).count() == spark.read.parquet(f"{SF001}/pages.parquet").count()


# ---- decontamination ------------------------------------------------------------------------------------------


def brute_contamination(rows, items):
    win = defaultdict(set)
    for i, t in items:
        for w in decontaminate.windows_of(words_of(t or "")):
            win[w].add(None if i is None else str(i))  # items without an id hit, count as one and are not listed
    lens = {len(w) for w in win}
    out = []
    for i, t in rows:
        words = words_of(t or "")
        hit, found = set(), set()
        for n in lens:
            for k in range(len(words) - n + 1):
                w = tuple(words[k : k + n])
                if w in win:
                    hit.update(range(k, k + n))
                    found |= win[w]
        out.append((i, len(words), len(hit), len(found), hashlib.sha256(",".join(sorted(x for x in found if x is not None)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(words)))
    return Counter(out)


def test_contamination(spark, docs, odd):
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF001}/benchmark.parquet").collect()] + [(900, "one two"), (901, "One, TWO"), (902, None), (903, ""), (None, "one two three"), (10, "the"), (9, "the")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    names = ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
    for part in (docs, odd):
        want = brute_contamination(collected(part), items)
        for block in (200_000, 150):  # the benchmark at once, and in several passes
            got = decontaminate.contamination(part, bench, window_block=block).select(*names)
            assert Counter(map(tuple, got.collect())) == want
    assert decontaminate.contamination(odd, bench.limit(0)).agg(F.sum("n_hit")).first()[0] == 0
    assert decontaminate.contamination(odd.limit(0), bench).count() == 0


def test_words_of_bytes(docs, odd):
    """Bytes are split into the words of the rule, whatever stands between and in them."""
    every = " ".join(map(chr, range(0xD800))) + "".join(f"a{chr(c)}B" for c in range(0x3000)) + "\u2028Ö\U0001f600x"
    for t in [every, "", "   ", *(t or "" for part in (docs, odd) for _, t in collected(part))]:
        assert [w.decode() for w in word_bytes(t.encode())] == words_of(t)


def test_proximity(spark):
    d = spark.createDataFrame([(1, "a x b c y a b"), (2, "c b"), (3, "a b")], "doc_id long, text string")
    got = sorted(map(tuple, decontaminate.proximity_hits(decontaminate.build_index(d), ["a", "b"], 3).collect()))
    assert got == [(1, 0, 3), (1, 5, 7), (3, 0, 2)]  # all stretches within three words that hold no narrower one


def test_clashing_names_and_limits(spark):
    """Columns named like the operators' own come through; giant canvases and long chunks are defined."""
    d = spark.createDataFrame([(k, f"line {k % 3} of some words here\nsecond line {k % 4} with other words", f"s{k % 2}", 7) for k in range(12)], "doc_id long, text string, source string, own_hash int")
    taken = ["own_hash", "own_id", "gone_id", "gone_whole", "first_class", "first_id", "src_name", "src_no", "row_hash", "row_group", "at_no", "placed", "__h", "__s", "__own", "__p", "__class", "__gone", "__text", "__media", "text_bytes", "n", "k", "u", "h", "g"]
    d = d.select("doc_id", "text", "source", *[F.lit(7).alias(c) for c in taken])
    for out in (line_dedup.dedup_lines(d), mixing.mix(d), near_dup.drop_near_duplicates(d)):
        rows = out.select(*taken).collect()
        assert rows and all(tuple(r) == (7,) * len(taken) for r in rows)
    keep = ("doc_id", "__text", "__media", "own")
    d = d.withColumn("own", F.lit(7))
    model = language_id.fit(d.withColumn("lang", F.lit("en")), F.lit(True))
    for out in (token_counts.count_tokens(d, keep=keep), gif.encode_texts(d, keep=keep), language_id.predict(d, model, keep=keep), gif.decode_frames(gif.encode_texts(d, keep=keep), keep=keep)):
        assert all((r["__text"], r["__media"], r["own"]) == (7, 7, 7) for r in out.collect())
    giant = b"GIF89a" + (65535).to_bytes(2, "little") * 2 + b"\0\0\0" + b"\x2c" + bytes(4) + (65535).to_bytes(2, "little") * 2 + b"\0\x08\x01\x00\x00\x3b"
    assert list(gif.decode(giant)) == []
    counter = token_counts.ChunkCounter(token_counts.tokenizer_path())
    long = ("x1" * 3000).encode()
    assert counter.cuts and counter.count([long + b" a", long])[1] == len(counter.tok.encode(long.decode(), add_special_tokens=False)) and all(len(c) <= 256 for c in counter.known)
    counter.cuts = False
    assert counter.count([b"whole  text", b""]).tolist() == [len(counter.tok.encode("whole  text", add_special_tokens=False)), 0]


# ---- line dedup -------------------------------------------------------------------------------------------------


def brute_lines(rows, min_lines, long_words):
    key = lambda i, t: (i is not None, i or 0)
    seqs = {}
    for i, t in rows:
        if t is not None:
            seqs[(i, t)] = [(k, x.strip(" ")) for k, x in enumerate(t.split("\n")) if x.strip(" ")]
    order = sorted(seqs, key=lambda x: key(*x))
    one, many = {}, {}
    for doc in order:
        q = [x for _, x in seqs[doc]]
        for j, x in enumerate(q):
            one.setdefault(x, (doc, j))
            if j + min_lines <= len(q):
                many.setdefault(tuple(q[j : j + min_lines]), (doc, j))
    out = {}
    for doc in order:
        q = [x for _, x in seqs[doc]]
        gone = set()
        for j, x in enumerate(q):
            if one[x] != (doc, j) and len(re.split(r"\s+", x)) >= long_words:
                gone.add(j)
            if j + min_lines <= len(q) and many[tuple(q[j : j + min_lines])] != (doc, j):
                gone.update(range(j, j + min_lines))
        drop = {seqs[doc][j][0] for j in gone}
        runs = sum(j - 1 not in gone for j in gone)
        out[doc] = ("\n".join(x for k, x in enumerate(doc[1].split("\n")) if k not in drop), len(q), len(gone), runs)
    return out


@pytest.mark.parametrize(("min_lines", "long_words"), [(2, 8), (3, 100), (1, 1), (5, 100)])
def test_line_dedup(docs, odd, min_lines, long_words):
    for part in (docs, odd):
        rows = collected(part)
        want = brute_lines(rows, min_lines, long_words)
        got = line_dedup.dedup_lines(part.withColumn("text0", F.col("text")), min_lines=min_lines, long_words=long_words).collect()
        assert len(got) == len(rows)
        for r in got:
            expect = (None, 0, 0, 0) if r.text0 is None else want[(r.doc_id, r.text0)]
            assert (r.text, r.n_lines, r.n_removed, r.n_runs) == expect


def test_suffix_array_order(spark):
    d = spark.createDataFrame([(1, "a\nb\na\nb\nc"), (2, "b\na\nb\nc\nd"), (3, "e")], "doc_id long, text string")
    lines = line_dedup.line_table(d, "text", "doc_id")
    sa = line_dedup.suffix_array(lines, 4).collect()
    seq = {1: "ababc", 2: "babcd", 3: "e"}
    for r in sa:
        own = seq[r.d][r.i :]
        common = max(next((k for k in range(5) if own[: k + 1] != o[: k + 1] or k >= len(own) or k >= len(o)), 0) for d2, s in seq.items() for i in range(len(s)) if (d2, i) != (r.d, r.i) for o in [s[i:]])
        assert r.lcp_at_least == max([p for p in (1, 2, 4) if p <= common], default=0)
    named = [r for r in sa if r.lcp_at_least >= 2]
    for x in named:
        for y in named:
            if x.lcp_at_least == y.lcp_at_least:
                k = x.lcp_at_least
                assert (x.sa_name == y.sa_name) == (seq[x.d][x.i : x.i + k] == seq[y.d][y.i : y.i + k])
    assert line_dedup.dedup_lines(d.limit(0)).count() == 0


def test_repeated_runs(docs, spark):
    """Runs are true copies of their sources, cover all later windows of two, and long passages come out whole."""
    rng = random.Random(8)
    passage = [prose(rng, 4) for _ in range(23)]
    more = spark.createDataFrame([(10**6, "\n".join([prose(rng, 5), *passage, prose(rng, 5)])), (10**6 + 1, "\n".join([*passage, "", prose(rng, 6)])), (10**6 + 2, "\n".join(passage[3:17]))], "doc_id long, text string")
    both = docs.select("doc_id", "text").unionByName(more)
    texts = {r.doc_id: r.text for r in both.collect() if r.text}
    seq = {d: [x.strip(" ") for x in t.split("\n") if x.strip(" ")] for d, t in texts.items()}
    runs = line_dedup.repeated_runs(both).collect()
    covered = defaultdict(set)
    for r in runs:
        assert r.lines >= 2 and (r.source_d, r.source_start) < (r.d, r.start)
        assert seq[r.d][r.start : r.start + r.lines] == seq[r.source_d][r.source_start : r.source_start + r.lines]
        covered[r.d].update(range(r.start, r.start + r.lines))
    firsts, seen, want = {}, set(), defaultdict(set)
    for d in sorted(seq):
        copy = texts[d] in firsts and len(seq[d]) > 1
        firsts.setdefault(texts[d], d)
        for i in range(len(seq[d]) - 1):
            pair = (seq[d][i], seq[d][i + 1])
            if pair in seen and not copy:
                want[d].update((i, i + 1))
            seen.add(pair)
    assert dict(covered) == dict(want)
    planted = {(r.d, r.start, r.lines, r.source_d, r.source_start) for r in runs if r.d >= 10**6}
    assert planted == {(10**6 + 1, 0, 23, 10**6, 1), (10**6 + 2, 0, 14, 10**6, 4)}


# ---- near duplicates ------------------------------------------------------------------------------------------------


def brute_near(rows, threshold=0.8):
    ids = WordIds()
    sets = [set(near_dup.shingle_set(t, ids).tolist()) if t else set() for _, t in rows]
    n = len(rows)
    links = [set() for _ in rows]
    for a in range(n):
        for b in range(a):
            x, y = sets[a], sets[b]
            same = rows[a][1] == rows[b][1] and rows[a][1] is not None
            if same or (x and y and len(x & y) >= threshold * len(x | y) - 1e-9):
                links[a].add(b)
                links[b].add(a)
    label = list(range(n))
    changed = True
    while changed:
        changed = False
        for a in range(n):
            low = min([label[a], *[label[b] for b in links[a]]])
            if low < label[a]:
                label[a], changed = low, True
    return links, label


@pytest.mark.parametrize(("small", "block"), [(16, 256), (1, 2)])
def test_near_duplicates(odd, docs, small, block):
    for part in (odd, docs):
        rows = collected(part)
        links, label = brute_near(rows)
        got = near_dup.join(part, small=small, block=block).collect()
        assert len(got) == len(rows)
        want = Counter()
        for a, (i, _) in enumerate(rows):
            ids = [rows[b][0] for b in range(len(rows)) if label[b] == label[a]]
            want[(i, None if None in ids else min(ids), len(links[a]))] += 1
        assert Counter((r.d, r.class_id, r.n_links) for r in got) == want
        kept = near_dup.drop_near_duplicates(part)
        assert kept.columns == part.columns and kept.count() == len(set(label))
    assert near_dup.join(odd.limit(0)).count() == 0


def test_recall_on_more_documents(spark):
    """All links of the sf 0.01 texts at 0.8 or more, found by an inverted index over whole sets."""
    docs = spark.read.parquet(SF001.replace("sf0.001", "sf0.01") + "/documents.parquet")
    rows = collected(docs)
    ids = WordIds()
    sets = [set(near_dup.shingle_set(t, ids).tolist()) if t else set() for _, t in rows]
    holders, shared = defaultdict(list), Counter()
    for k, own in enumerate(sets):
        for s in own:
            shared.update((j, k) for j in holders[s])
            holders[s].append(k)
    links = {(a, b) for (a, b), n in shared.items() if n >= 0.8 * (len(sets[a]) + len(sets[b]) - n) - 1e-9}
    alike = defaultdict(list)
    for k, (_, t) in enumerate(rows):
        if t is not None:
            alike[t].append(k)
    links |= {(a, b) for group in alike.values() for i, b in enumerate(group) for a in group[:i]}
    want = Counter(rows[k][0] for pair in links for k in pair)
    got = {r.d: r.n_links for r in near_dup.join(docs).collect() if r.n_links}
    assert len(links) > 100 and all(n <= want[d] for d, n in got.items())
    assert sum(got.values()) >= 0.99 * sum(want.values())


def test_bands_reach_the_recall():
    for t, recall in ((0.8, 0.99999), (0.6, 0.99), (0.9, 0.999)):
        bands, rows = near_dup.bands_for(t, recall)
        assert 1 - (1 - t**rows) ** bands >= recall and bands * rows <= 160


# ---- long byte matches -------------------------------------------------------------------------------------------------


def brute_bytes(rows, width=50):
    first = {}
    for i, t in rows:
        b = (t or "").encode()
        if i is not None:
            for p in range(len(b) - width + 1):
                w = b[p : p + width]
                first[w] = min(first.get(w, i), i)
    out = Counter()
    for i, t in rows:
        b = (t or "").encode()
        g = np.zeros(len(b), bool)
        if i is not None:
            for p in range(len(b) - width + 1):
                if first[b[p : p + width]] < i:
                    g[p : p + width] = True
        kept = np.frombuffer(b, np.uint8)[~g].tobytes()
        spans = int(g[:1].sum() + (g[1:] & ~g[:-1]).sum())
        out[(i, len(b), int(g.sum()), spans, hashlib.sha256(kept).hexdigest())] += 1
    return out


@pytest.mark.parametrize("crowd", [4096, 2])
def test_substring_dedup(spark, odd, docs, crowd):
    rng = random.Random(4)
    base = prose(rng, 300)
    mixed = []
    for k in range(80):  # passages that overlap in many ways
        a = rng.randrange(1200)
        s = list(base[a : a + rng.randrange(30, 300)])
        for _ in range(rng.randrange(3)):
            s[rng.randrange(len(s))] = rng.choice("xyz ")
        mixed.append((rng.randrange(60), "".join(s)))
    mixed += [(61, "x" * 300), (62, "ab" * 90), (63, "ab" * 40), (64, "y" * 49), (65, "y" * 50), (66, "y" * 51)]
    cases = [odd, spark.createDataFrame(mixed, "doc_id long, text string"), docs.where("doc_id < 120")]
    for part in cases:
        want = brute_bytes(collected(part))
        for block, bucket in ((1 << 20, 12 << 20), (700, 2000)):
            got = substring_dedup.remove_repeats(part, block_bytes=block, bucket_bytes=bucket, crowd=crowd).collect()
            assert Counter((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got) == want
            assert all(hashlib.sha256(r.kept).hexdigest() == r.kept_sha256 for r in got)
    assert substring_dedup.remove_repeats(odd.limit(0)).count() == 0


@settings(max_examples=40, deadline=None)
@given(st.lists(st.text(alphabet="ab", min_size=3, max_size=12), min_size=1, max_size=12))
def test_run_length_index(strings):
    strings = [s.encode() for s in dict.fromkeys(strings)]
    data, lens = np.frombuffer(b"".join(strings), np.uint8), np.asarray(list(map(len, strings)))
    width = 3
    index = RunLengthIndex(data, lens, width)
    assert index.runs <= index.n
    matched, interval = index.stream(data, lens)
    asked = np.unique(interval[interval >= 0])
    best = dict(zip(asked.tolist(), index.least(asked, np.arange(len(strings))).tolist(), strict=True))
    at = 0
    for s in strings:
        for p in range(len(s)):
            assert matched[at] == min(width, len(s) - p)
            if p + width <= len(s):
                assert best[int(interval[at])] == next(k for k, o in enumerate(strings) if s[p : p + width] in o)
            at += 1


@pytest.mark.parametrize("width", [2, 7, 8, 50])
def test_index_equals_sorted_suffixes(width):
    """Order, runs and ranks of the index against suffixes sorted one by one: repeats, ends and all bytes."""
    rng = random.Random(width)
    base = bytes(rng.choice(b"ab\x00\xff") for _ in range(150))
    strings = [base[a : a + rng.randrange(1, 90)] for a in (rng.randrange(120) for _ in range(60))] + [b"a" * 80, b"a" * 79, bytes(range(256))]
    lens = np.asarray(list(map(len, strings)))
    index = RunLengthIndex(np.frombuffer(b"".join(strings), np.uint8), lens, width)
    place = [(k, p) for k, s in enumerate(strings) for p in range(len(s) + 1)]
    key = lambda x: [c + 1 for c in strings[x[0]][x[1] :]] + [0, x[0]]
    order = sorted(place, key=key)
    number = {x: i for i, x in enumerate(place)}
    before = [strings[k][p - 1] if p else -1 for k, p in order]
    assert index.run_byte[index.run_of].tolist() == before
    assert [number[order[r - 1]] for r in index.close_row] == index.close_text.tolist()
    # a class: equal in ``width`` symbols, or alone where the end comes first
    classes = [strings[k][p : p + width] if p + width <= len(strings[k]) else (k, p) for k, p in order]
    assert [i for i, c in enumerate(classes) if not i or c != classes[i - 1]] == index.open_row.tolist()
    assert [number[x] for x in order[:-1]] == index.above(np.asarray([number[x] for x in order[1:]])).tolist()
    row = np.arange(index.n + 1)
    for c in (0, 97, 98, 255, 30):
        assert index.rank(np.full(len(row), c), row).tolist() == np.cumsum([0, *(b == c for b in before)]).tolist()


def test_lookup_searches_only_beside_runs(monkeypatch):
    """Where a run tells the rank nothing is searched: a step in few thousand rows searches for few."""
    rng = random.Random(9)
    base = prose(rng, 900).encode()
    strings = [base[a : a + 70] for a in range(0, len(base) - 70, 7)]
    searched = [0, 0]
    plain, whole = RunLengthIndex._rank_before, RunLengthIndex.rank
    monkeypatch.setattr(RunLengthIndex, "_rank_before", lambda self, c, r: (searched.__setitem__(0, searched[0] + len(r)), plain(self, c, r))[1])
    monkeypatch.setattr(RunLengthIndex, "rank", lambda self, c, r: (searched.__setitem__(1, searched[1] + len(r)), whole(self, c, r))[1])
    got = substring_dedup.look_up(b"".join(strings), np.asarray(list(map(len, strings))), np.arange(len(strings)), 50)
    first: dict[bytes, int] = {}
    want = [first.setdefault(s[p : p + 50], k) < k for k, s in enumerate(strings) for p in range(len(s) - 49)]
    assert got.tolist() == want and 0 < 2 * searched[0] < searched[1]


def test_stretches_with_clashing_keys_stay_apart(monkeypatch):
    """Within a block, stretches are equal only if their minimizers are as well."""
    rng = random.Random(5)
    texts = [prose(rng, 60).encode() for _ in range(6)]
    made = lambda: substring_dedup.Block(list(range(7)), [len(t) for t in [*texts, texts[0]]], b"".join([*texts, texts[0]]), 4, substring_dedup.WIDTH, substring_dedup.SHORT)
    plain = made()
    monkeypatch.setattr(substring_dedup, "stretch_keys", lambda data, start, stop, width, k: np.zeros(len(start), np.uint64))
    clash = made()
    m = [plain.u_min[plain.unique], clash.u_min[clash.unique]]
    assert len(set(clash.u_min.tolist())) == len(clash.u_min) > 1 and (m[0] == m[1]).all()


# ---- mixing -------------------------------------------------------------------------------------------------------------


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 50), min_size=1, max_size=8), st.integers(16, 200))
def test_pfair_deviation(weights, cycle):
    share = mixing.shares([float(w) for w in weights], max(cycle, len(weights)))
    slots = mixing.schedule_cycle(share)
    assert len(slots) == sum(share) == max(cycle, len(weights))
    done = [0] * len(share)
    for t, i in enumerate(slots, 1):
        done[i] += 1
        assert all(abs(done[k] - t * share[k] / sum(share)) < 1 for k in range(len(share)))
    assert done == share


def fluid_deviation(blocks, weights, owner):
    """Largest distance of the placed blocks of any source from its target, slot by slot in floats."""
    left, weight = np.asarray(blocks, float), np.asarray(weights, float)
    target, done, worst = np.zeros(len(left)), np.zeros(len(left)), 0.0
    for i in owner:
        time = 1.0
        while time > 1e-12:
            live = np.where(left - target > 1e-9, weight, 0.0)
            if not live.any():
                break
            rate = live / live.sum()
            step = min(time, np.min((left - target)[live > 0] / rate[live > 0]))
            target += rate * step
            time -= step
        done[i] += 1
        worst = max(worst, np.abs(done - target).max())
    return worst


def mixed(blocks, weights):
    names = [f"s{i:05d}" for i in range(len(blocks))]
    plan = mixing.plan(dict(zip(names, blocks, strict=True)), dict(zip(names, weights, strict=True)))
    assert ((plan.release <= plan.slot) & (plan.slot < plan.deadline)).all()
    assert sorted(plan.slot.tolist()) == list(range(sum(blocks)))
    return plan, np.repeat(np.arange(len(blocks)), blocks)[np.argsort(plan.slot)]


@pytest.mark.parametrize(
    ("blocks", "weights"),
    [([1250] * 20, [1.0] * 20), ([4, 9000, 9000], [0.0001, 0.49995, 0.49995]), ([300, 2000, 40, 3000], [0.3, 0.31, 2**0.5, 0.05]), ([5] * 40, [float(i) for i in range(1, 41)])],
)
def test_mixing_keeps_weights_over_many_cycles(blocks, weights):
    assert fluid_deviation(blocks, weights, mixed(blocks, weights)[1]) < 1 + 1e-6


def test_mixing_thousands_of_sources():
    weights = [3.0 if i % 2 else 1.0 for i in range(3000)]
    plan, owner = mixed([4] * 3000, weights)
    head = np.bincount(owner[:4000] % 2)  # 4,000 slots give sources of weight 3 two thirds of a block, the others two ninths
    assert 2 * head[0] < head[1]
    assert fluid_deviation([4] * 3000, weights, owner) < 1 + 1e-6
    phase = plan.place(np.array([1, 0]), np.array([0, 3]))[0]
    assert phase.tolist() == [0, 1]


def test_mixing_places_all(odd, docs):
    for part, options in ((odd, {"block_docs": 2}), (docs, {"block_docs": 4, "group_rows": 10}), (docs, {"weights": {"src0": 3.0, "src1": 1.0}, "block_docs": 3, "cycle": 64})):
        got = mixing.mix(part, **options).toPandas()
        assert len(got) == part.count() and got.mix_rank.is_unique
        assert ((got.mix_slot >= got.mix_release) & (got.mix_slot < got.mix_deadline)).all()
        assert sorted(got.mix_slot.unique()) == list(range(got.mix_slot.nunique()))
        per_block = got.groupby(["mix_slot"]).size()
        assert per_block.max() <= options["block_docs"] and got.groupby("mix_slot")["source"].nunique(dropna=False).max() == 1
        again = mixing.mix(part.repartition(5), **options).toPandas()
        assert sorted(zip(got.doc_id.fillna(-1), got.mix_rank, strict=True)) == sorted(zip(again.doc_id.fillna(-1), again.mix_rank, strict=True))
    assert mixing.mix(odd.limit(0)).count() == 0


# ---- pipeline -------------------------------------------------------------------------------------------------------------


def test_pipeline_stages(spark, docs):
    import corpus_pipeline

    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF001}/benchmark.parquet").collect()]
    junk = spark.createDataFrame([(9001, "12345 !!", "en", "s", 8), (9002, None, None, None, None), (9003, items[0][1], "en", "s", 5)], docs.schema)
    now = docs.unionByName(junk)
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language_id", "line_dedup", "near_duplicates", "decontamination", "mixing"]
    for name, stage in corpus_pipeline.STAGES:
        before = collected(now)
        out = stage(spark, now, SF001).cache()
        after = collected(out)
        assert set(now.columns) <= set(out.columns) and (name == "mixing" or out.columns == now.columns)
        if name == "language_id":
            assert Counter(after) == Counter((i, t) for i, t in before if t and re.search(r"[^\W\d_]", t))
        elif name == "line_dedup":
            want = brute_lines(before, 2, 8)
            assert Counter(after) == Counter((i, want[(i, t)][0]) for i, t in before if not 0 < want[(i, t)][1] == want[(i, t)][2])
        elif name == "near_duplicates":
            _, label = brute_near(before)
            best = {}
            for (i, _), k in zip(before, label, strict=True):
                best[k] = min(best.get(k, i), i)
            assert Counter(i for i, _ in after) == Counter(best.values())
        elif name == "decontamination":
            bad = {r[0] for r in brute_contamination(before, items) if r[5]}
            assert bad and Counter(after) == Counter((i, t) for i, t in before if i not in bad)
        else:
            assert Counter(after) == Counter(before)
        now = out


def test_pipeline_run(spark):
    import corpus_pipeline

    out = corpus_pipeline.run(spark, SF001)
    assert 0 < out.count() <= spark.read.parquet(f"{SF001}/documents.parquet").count() and "mix_rank" in out.columns
