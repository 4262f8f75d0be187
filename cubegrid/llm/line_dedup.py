"""Line deduplication over line-ID sequences by a suffix array made with distributed prefix doubling.

Every non-blank line gets an ID from its content; a document is a sequence of IDs. A round of
doubling names the window of 2k lines at a position by the pair of names of its two halves, sorts
the distinct pairs by range over the cluster and takes the order as the new, order-preserving
name. Windows that occur once can never again be part of a repeat, so they are discarded; rounds go on
until nothing repeats, however long the longest repeat is.

The positions that bear one name after a round are the suffixes that share so many lines: an interval of
the suffix array whose longest common prefix has at least that depth, with its number of suffixes and its
first position. The intervals of depths 1, 2, 4, ... are nested. A position's deepest interval in
which it is not the first begins a repeated run there, and as a run of any length is covered by the
windows of that power of two which begin and end it, the union of these windows is the union of
all maximal repeated runs: lines are deleted if that union covers them. ``repeated_runs`` lists the runs
themselves: neighbouring windows whose first copies lie at one distance are one run, grown until it ends
on both sides.

A run counts if it has ``min_lines`` lines, or is one line of ``long_words`` words or more; of each
such run only the copy first in order (doc_id, line) stays. A shorter single line stays in every copy.
The number of runs of a document counts stretches of neighbouring deleted lines.

Documents with equal texts are one sequence of the array (a pre-aggregation; the later ones are later
copies as a whole), equal pairs are counted before they are sorted, and names come back to positions
by a join that spreads the hot ones, so a line that stands in a third of all documents is one row in the
first and many small parts in the second.

Defined results: null text has no lines and stays null; blank lines are kept and no part of runs;
rows with equal doc_id and text are one document and get the same result; null ids come first in
order. Columns not named are carried along whatever their names; one named like a count is replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubegrid.llm.common import fresh, join_hot, stored

_DOC = ["d", "h"]
#: Places to delete are kept in parts of so many lines, so that testing a line stays short in very long texts.
_CHUNK = 1024


def _pos() -> Column:
    return F.struct("d", "h", "i")


def line_table(docs: DataFrame, text: str, doc_id: str) -> DataFrame:
    """One row per non-blank line: document (d, h; g is a second hash of its text, u its row), number of its
    lines, the line's number i, its place in the text, ID and words."""
    lines = F.filter(F.transform(F.split(F.col("t"), "\n", -1), lambda x, i: F.struct(i.alias("at"), F.trim(x).alias("s"))), lambda x: x["s"] != "")
    body = F.col(f"`{text}`")
    base = docs.select(F.col(f"`{doc_id}`").cast("long").alias("d"), F.xxhash64(body).alias("h"), F.xxhash64(F.lit(7), body).alias("g"), F.monotonically_increasing_id().alias("u"), body.alias("t")).where("t is not null")
    each = base.select("d", "h", "g", "u", lines.alias("all")).select("d", "h", "g", "u", F.size("all").alias("lines"), F.posexplode("all").alias("i", "line"))
    return each.select("d", "h", "g", "u", "lines", "i", F.col("line.at").alias("at"), F.xxhash64("line.s").alias("l1"), F.hash("line.s").alias("l2"), F.size(F.split("line.s", r"\s+")).alias("words"))


def sequences(lines: DataFrame, least_lines: int) -> tuple[DataFrame, DataFrame]:
    """(lines of one document of each text, documents that are later copies of a whole text: d, h, lines).

    Texts of fewer than ``least_lines`` lines all stay, as a copy of them is no run by itself.
    """
    heads = lines.where((F.col("i") == 0) & (F.col("lines") >= least_lines))
    groups = stored(heads.groupBy("h", "g").agg(F.count("*").alias("n"), F.min(F.struct("d", "u")).alias("own")).where("n > 1"), "line-copies")
    of = lambda rows: join_hot(rows, groups, ["h", "g"], "n", "left")
    kept = of(lines).where(F.col("own").isNull() | (F.col("lines") < least_lines) | (F.col("u") == F.col("own.u")))
    copies = of(heads).where(F.col("own").isNotNull() & ~F.col("d").eqNullSafe(F.col("own.d")))
    return kept.select("d", "h", "i", "at", "l1", "l2", "words"), copies.select("d", "h", "lines").distinct()


def _named(rows: DataFrame, keys: list[str], name: str) -> DataFrame:
    """Distinct keys that occur twice or more, with an order-preserving name, count and first position.

    After a range sort over the cluster, partition number and row number together rise with the
    key; the table is written, so a name never changes when executors are lost.
    """
    classes = rows.groupBy(*keys).agg(F.count("*").alias("n"), F.min(_pos()).alias("first")).where("n > 1")
    ordered = classes.repartitionByRange(*keys).sortWithinPartitions(*keys)
    return stored(ordered.withColumn("name", F.monotonically_increasing_id()), name)


def _step(rows: DataFrame, depth: int, shift: int) -> DataFrame:
    """Names of windows of ``depth + shift`` lines: pairs of the names at i and i + shift."""
    to = depth + shift
    ahead = F.max("name").over(Window.partitionBy(*_DOC).orderBy("i").rangeBetween(shift, shift))
    pairs = stored(rows.select("d", "h", "i", F.col("name").alias("a"), ahead.alias("b")).where("b is not null"), f"line-pairs-{to}")
    return stored(join_hot(pairs, _named(pairs, ["a", "b"], f"line-names-{to}"), ["a", "b"], "n").select("d", "h", "i", "name", "first"), f"line-windows-{to}")


def intervals(seqs: DataFrame, least_lines: int = 2, most: int | None = None) -> dict[int, DataFrame]:
    """Per depth 1, 2, 4, ... (and ``least_lines``) the positions whose window of so many lines repeats:
    d, h, i, name (order-preserving: the interval of the suffix array) and first (its first position).

    Doubling ends when nothing repeats, or beyond ``most`` lines.
    """
    ids = _named(seqs, ["l1", "l2"], "line-names")
    single = join_hot(seqs, ids, ["l1", "l2"], "n").select("d", "h", "i", "at", "words", "name", "first")
    out, k = {1: stored(single, "line-repeats")}, 1
    while (most is None or 2 * k <= most) and not out[k].isEmpty():
        if k < least_lines < 2 * k:
            out[least_lines] = _step(out[k], k, least_lines - k)
        out[2 * k] = _step(out[k], k, k)
        k *= 2
    return out


def suffix_array(lines: DataFrame, longest: int) -> DataFrame:
    """All positions with ``sa_name`` (order of suffixes by their first ``longest`` lines, equal if those agree)
    and ``lcp_at_least``: the greatest power of two up to ``longest`` at which the window repeats."""
    levels = intervals(lines, 1, longest)
    found = None
    for k, rows in levels.items():
        part = rows.select("d", "h", "i", F.lit(k).alias("k"), "name")
        found = part if found is None else found.unionByName(part)
    best = found.groupBy("d", "h", "i").agg(F.max("k").alias("k"), F.max_by("name", "k").alias("sa_name"))
    same = [F.col("d").eqNullSafe(F.col("d2")), F.col("h") == F.col("h2"), F.col("i") == F.col("i2")]
    joined = lines.select("d", "h", "i").join(best.select(F.col("d").alias("d2"), F.col("h").alias("h2"), F.col("i").alias("i2"), "k", "sa_name"), same, "left")
    return joined.select("d", "h", "i", F.coalesce("k", F.lit(0)).alias("lcp_at_least"), "sa_name")


def _later(levels: dict[int, DataFrame]) -> DataFrame:
    """Positions that are later copies: d, h, i, at, words, depth and first of the deepest interval in which
    they are not first; dealt and sorted by document."""
    parts = None
    for k, rows in levels.items():
        own = (F.col("at"), F.col("words")) if k == 1 else (F.lit(None).cast("int").alias("at"), F.lit(None).cast("int").alias("words"))
        part = rows.where(F.col("first") < _pos()).select("d", "h", "i", *own, F.lit(k).alias("depth"), "first")
        parts = part if parts is None else parts.unionByName(part)
    dealt = parts.repartition(*[F.col(c) for c in _DOC])
    return dealt.groupBy("d", "h", "i").agg(F.max("at").alias("at"), F.max("words").alias("words"), F.max("depth").alias("depth"), F.max_by("first", "depth").alias("first"))


def repeated_runs(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", min_lines: int = 2) -> DataFrame:
    """The maximal runs of lines that stand in an earlier place too: d, h, start, lines, and where their
    first copy begins (source_d, source_h, source_start). Lines are numbered without blank ones; of
    documents with equal texts only the first is listed."""
    seqs, _ = sequences(stored(line_table(docs, text, doc_id), "lines"), min_lines)
    rows = _later(intervals(seqs, min_lines))
    w = Window.partitionBy(*_DOC).orderBy("i")
    align = F.struct("first.d", "first.h", (F.col("first.i") - F.col("i")).alias("off"))
    begins = F.lag("i").over(w).isNull() | (F.lag("i").over(w) != F.col("i") - 1) | ~F.lag(align).over(w).eqNullSafe(align)
    runs = rows.withColumn("run", F.sum(begins.cast("int")).over(w)).groupBy("d", "h", "run")
    out = runs.agg(F.min("i").alias("start"), (F.max(F.col("i") + F.col("depth")) - F.min("i")).alias("lines"), F.min_by("first", "i").alias("first"))
    return out.where(F.col("lines") >= min_lines).select("d", "h", "start", "lines", F.col("first.d").alias("source_d"), F.col("first.h").alias("source_h"), F.col("first.i").alias("source_start"))


def later_copies(docs: DataFrame, text: str, doc_id: str, min_lines: int, long_words: int) -> DataFrame:
    """Per document with lines to delete: d, h, whether all of them go, else their places in lists of a
    fixed span each, runs, n."""
    seqs, copies = sequences(stored(line_table(docs, text, doc_id), "lines"), min_lines)
    rows = _later(intervals(seqs, min_lines))
    w = Window.partitionBy(*_DOC).orderBy("i")
    reach = F.max(F.when(F.col("depth") >= min_lines, F.col("i") + F.col("depth"))).over(w.rowsBetween(Window.unboundedPreceding, 0))
    hits = rows.select("d", "h", "i", "at", (F.coalesce(reach > F.col("i"), F.lit(False)) | (F.col("words") >= long_words)).alias("gone")).where("gone")
    begins = F.coalesce(F.lag("i").over(w) < F.col("i") - 1, F.lit(True)).cast("long")
    parts = hits.select("d", "h", "at", begins.alias("begins")).groupBy("d", "h", F.expr(f"at div {_CHUNK}").cast("int").alias("part")).agg(F.collect_list("at").alias("at"), F.sum("begins").alias("runs"), F.count("*").alias("n"))
    gone = F.map_from_entries(F.collect_list(F.struct("part", "at")))
    some = parts.groupBy("d", "h").agg(F.lit(False).alias("whole"), gone.alias("gone"), F.sum("runs").alias("runs"), F.sum("n").alias("n"))
    return some.unionByName(copies.select("d", "h", F.lit(True).alias("whole"), F.lit(1).cast("long").alias("runs"), F.col("lines").cast("long").alias("n")), allowMissingColumns=True)


def dedup_lines(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", min_lines: int = 2, long_words: int = 8, counts: tuple[str, str, str] = ("n_lines", "n_removed", "n_runs")) -> DataFrame:
    """All rows and columns, ``text`` without later copies, plus three counts (replacing columns so named)."""
    rows = docs.drop(*counts)
    gone = later_copies(docs, text, doc_id, min_lines, long_words)
    h, d, gd, gh, whole, places, runs, n = fresh([*docs.columns, *counts], "own_hash", "own_id", "gone_id", "gone_hash", "gone_whole", "gone_places", "gone_runs", "gone_n")
    body = F.col(f"`{text}`")
    keyed = rows.withColumn(h, F.xxhash64(body)).withColumn(d, F.col(f"`{doc_id}`").cast("long"))
    gone = gone.select(F.col("d").alias(gd), F.col("h").alias(gh), F.col("whole").alias(whole), F.col("gone").alias(places), F.col("runs").alias(runs), F.col("n").alias(n))
    joined = keyed.join(gone, F.col(d).eqNullSafe(F.col(gd)) & (F.col(h) == F.col(gh)), "left")
    lines = F.split(body, "\n", -1)
    # a line looks into the part of the list where its own number would stand
    kept = F.array_join(F.filter(lines, lambda x, i: ~F.coalesce(F.array_contains(F.element_at(places, F.call_function("div", i, F.lit(_CHUNK)).cast("int")), i), F.lit(False))), "\n")
    blank = F.array_join(F.filter(lines, lambda x: F.trim(x) == ""), "\n")
    cut = F.when(F.col(whole).isNull(), body).when(F.col(whole), blank).otherwise(kept)
    n_lines = F.when(body.isNull(), 0).otherwise(F.size(F.filter(lines, lambda x: F.trim(x) != "")))
    return joined.select(
        *[cut.alias(c) if c == text else F.col(f"`{c}`") for c in rows.columns],
        n_lines.cast("long").alias(counts[0]),
        F.coalesce(n, F.lit(0)).cast("long").alias(counts[1]),
        F.coalesce(runs, F.lit(0)).cast("long").alias(counts[2]),
    )


def op7_line_dedup(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_lines, n_removed, n_runs, and size and digest of the text that is left."""
    from cubegrid.llm.common import table

    out = dedup_lines(table(spark, sf_dir, "documents"))
    left = F.coalesce(F.col("text"), F.lit(""))
    return out.select("doc_id", "n_lines", "n_removed", "n_runs", F.length(left).cast("long").alias("kept_chars"), F.sha2(left, 256).alias("kept_sha256"))
