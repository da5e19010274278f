"""Line deduplication by a suffix array over line-ID sequences, in DataFrame functions only.

Every line is a 128-bit ID, every document a sequence of IDs. Prefix doubling ranks the suffixes by their first 1, 2, 4, ...
lines: a window's rank is paired with that of the window after it in its document, and the distinct pairs are sorted over
the cluster by range; the place in that order is the new rank. Equal ranks are an interval of the suffix array whose common
prefix has 2^k lines. A window that occurs once repeats nothing and leaves, and so does, before the doubling, every stretch
of repeated lines with fewer than MIN_WORDS words in all.

The longest-common-prefix intervals in between come from going back down the ranks, longest first: an interval of the prefix
length l splits by the rank of the 2^k lines that follow, into intervals of length l + 2^k. The first suffix of a new interval,
in (doc_id, row, line) order, stays in the outer one and stands for the new one there; all others move in, having an earlier
copy of that length. After the last rank each suffix knows the longest run of lines at its place that occurs earlier, from
one and the same place. Runs of MIN_WORDS words or more are deleted. An interval is named by its first suffix and its length.

Every step is an aggregation with partial sums or a join on keys that adaptive execution can split; the empty line, the
commonest of all, takes part without being counted or joined.

Defined cases: null text stays null and empty text stays empty, both without repeats; rows that repeat (doc_id and text) are
documents of their own, the first read row being the first copy; a null doc_id sorts first; lines are equal only when all of
their characters are, and among equal runs the least (doc_id, row, line) is the first; a run may overlap its earlier copy
in the same text; a document whose lines are all later copies keeps an empty text; very long texts need their lines, not their
windows, in one task; an empty table gives an empty result; extra columns are kept as they are, whatever their names (the two that
are added can be named otherwise).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from gridmul.llm.common import fresh, materialise

MIN_WORDS = 50
UID = "_gm_uid"
#: Rank of the empty line.
EMPTY = -1
#: Name of the interval of all suffixes.
ROOT = -1


def _ranked(windows: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, rank) of the keys that occur twice or more; ranks grow with the keys' order."""
    classes = windows.groupBy(*keys).agg(F.count("*").alias("n")).where("n > 1").drop("n")
    # the identifier grows with the range partition and within it: the place in the sorted order, up to gaps
    return classes.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("rank", F.monotonically_increasing_id())


def repeated_lines(docs: DataFrame, id_col: str, text_col: str, min_words: int, uid: str) -> DataFrame:
    """(doc, uid, pos, rank, words): repeated lines in stretches of min_words words or more."""
    lines = docs.where(F.col(text_col).isNotNull()).select(F.col(id_col).alias("doc"), F.col(uid).alias("uid"), F.posexplode(F.split(F.col(text_col).cast("string"), "\n", -1)).alias("pos", "line"))
    words = F.expr(r"CAST(regexp_count(line, r'\S+') AS int)")
    # two hashes with different starts make a line's ID; the empty line has none
    filled = F.col("line") != ""
    lines = materialise(lines.select("doc", "uid", "pos", F.when(filled, F.xxhash64("line")).alias("k1"), F.when(filled, F.xxhash64(F.lit(1), "line")).alias("k2"), words.alias("words")), "lines", narrow=True)
    named = lines.where("k1 IS NOT NULL")
    empty = lines.where("k1 IS NULL").select("doc", "uid", "pos", F.lit(EMPTY).cast("long").alias("rank"), "words")
    found = named.join(_ranked(named, ["k1", "k2"]), ["k1", "k2"]).select("doc", "uid", "pos", "rank", "words").unionByName(empty)
    stretch = found.withColumn("stretch", F.col("pos") - F.row_number().over(Window.partitionBy("uid").orderBy("pos")))
    heavy = stretch.withColumn("all_words", F.sum("words").over(Window.partitionBy("uid", "stretch"))).where(F.col("all_words") >= min_words)
    return materialise(heavy.drop("stretch", "all_words"), "lines-windows", narrow=True)


def ranks(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS, levels: int | None = None, uid: str = UID) -> list[DataFrame]:
    """(doc, uid, pos, rank, words) of the repeated windows of 1, 2, 4, ... lines, until none repeats (or so many levels)."""
    out = [repeated_lines(docs, id_col, text_col, min_words, uid)]
    while not out[-1].isEmpty() and (levels is None or len(out) < levels):
        step = 1 << len(out) - 1
        after = Window.partitionBy("uid").orderBy("pos").rangeBetween(step, step)
        # a window of twice the length repeats only where both of its halves do
        pairs = out[-1].select("doc", "uid", "pos", F.col("rank").alias("k1"), F.max("rank").over(after).alias("k2"), (F.col("words") + F.max("words").over(after)).alias("words")).where("k2 IS NOT NULL")
        out.append(materialise(pairs.join(_ranked(pairs, ["k1", "k2"]), ["k1", "k2"]).select("doc", "uid", "pos", "rank", "words"), "lines-windows", narrow=True))
    return out[:-1] if out[-1].isEmpty() else out


def _row(a_uid: str, a_pos: str, length: Column, words: Column) -> Column:
    return F.struct(F.col(a_uid).alias("a_uid"), F.col(a_pos).alias("a_pos"), length.alias("length"), "doc", "uid", "pos", words.alias("words"))


def longest_earlier(levels: list[DataFrame]) -> DataFrame:
    """(uid, pos, length, words): the longest run at each repeated place that also occurs earlier."""
    state = None
    own = "a_uid, a_pos, length, doc, uid, pos, words"
    for k in reversed(range(len(levels))):
        step, window = 1 << k, levels[k]
        tested = window.select(F.lit(ROOT).cast("long").alias("a_uid"), F.lit(ROOT).alias("a_pos"), F.lit(0).alias("length"), "doc", "uid", "pos", F.lit(0).alias("words"), F.col("rank").alias("next"), F.col("words").alias("more"))
        if state is not None:
            inside = state.where("uid <> a_uid OR pos <> a_pos").select("uid", "pos")
            follow = window.select(F.col("uid").alias("n_uid"), F.col("pos").alias("n_pos"), F.col("rank").alias("next"), F.col("words").alias("more"))
            tested = tested.join(inside, ["uid", "pos"], "left_anti").select(*tested.columns).unionByName(state.join(follow, (F.col("uid") == F.col("n_uid")) & (F.col("pos") + F.col("length") == F.col("n_pos")), "left").drop("n_uid", "n_pos"))
        interval = ["a_uid", "a_pos", "length", "next"]
        split = tested.where("next IS NOT NULL").groupBy(*interval).agg(F.count("*").alias("n"), F.min(F.struct("doc", "uid", "pos")).alias("first")).where("n > 1").select(*interval, F.col("first.uid").alias("f_uid"), F.col("first.pos").alias("f_pos"))
        placed = tested.join(split, interval, "left")
        stays, deeper = _row("a_uid", "a_pos", F.col("length"), F.col("words")), _row("f_uid", "f_pos", F.col("length") + step, F.col("words") + F.col("more"))
        at_root, leads = F.col("a_uid") == ROOT, (F.col("uid") == F.col("f_uid")) & (F.col("pos") == F.col("f_pos"))
        rows = F.when(F.col("f_uid").isNull(), F.when(~at_root, F.array(stays))).when(leads, F.when(at_root, F.array(deeper)).otherwise(F.array(stays, deeper))).otherwise(F.array(deeper))
        state = materialise(placed.select(F.inline(rows)), "lines-intervals", narrow=True)
    return state.where("uid <> a_uid OR pos <> a_pos").select("uid", "pos", "length", "words")


def repeated_ranges(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS, levels: int | None = None, uid: str = UID) -> DataFrame:
    """(uid, start, end): line ranges covered by later copies of runs of at least min_words words. docs must hold uid."""
    windows = ranks(docs, id_col, text_col, min_words, levels, uid)
    if not windows:
        return docs.select(F.col(uid).alias("uid"), F.lit(0).alias("start"), F.lit(0).alias("end")).where("false")
    runs = longest_earlier(windows).where(F.col("words") >= min_words).select("uid", F.col("pos").alias("start"), (F.col("pos") + F.col("length")).alias("end"))
    in_order = Window.partitionBy("uid").orderBy("start")
    fresh = (F.col("start") > F.coalesce(F.max("end").over(in_order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(-1))).cast("int")
    islands = runs.withColumn("fresh", fresh).withColumn("island", F.sum("fresh").over(in_order))
    return islands.groupBy("uid", "island").agg(F.min("start").alias("start"), F.max("end").alias("end")).select("uid", "start", "end")


def with_uid(docs: DataFrame, uid: str = UID) -> DataFrame:
    """docs with a number for each row, written so that it stays the same."""
    return materialise(docs.withColumn(uid, F.monotonically_increasing_id()), "lines-docs")


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS, levels: int | None = None, lines_col: str = "_gm_lines", removed_col: str = "_gm_removed") -> DataFrame:
    """All columns of docs, the text without later copies, and two counts of lines: all and removed ones. levels: of prefix
    doubling; None: all."""
    if taken := {lines_col, removed_col} & set(docs.columns):
        raise ValueError(f"name the counts otherwise: {sorted(taken)}")
    uid = fresh(docs, UID)
    numbered = with_uid(docs, uid)
    found = fresh(docs, "_gm_ranges")
    ranges = repeated_ranges(numbered, id_col, text_col, min_words, levels, uid)
    per_row = ranges.groupBy("uid").agg(F.collect_set(F.struct("start", "end")).alias(found)).withColumnRenamed("uid", uid)
    joined = numbered.join(per_row, uid, "left")
    whole = F.col(f"`{text_col}`")
    lines = F.split(whole.cast("string"), "\n", -1)
    clean = F.col(found).isNull()
    left = F.when(clean, lines).otherwise(F.filter(lines, lambda line, i: ~F.exists(F.col(found), lambda r: (r["start"] <= i) & (i < r["end"]))))
    n = F.when(whole.isNull(), 0).otherwise(F.size(lines))
    gone = F.when(clean | whole.isNull(), 0).otherwise(n - F.size(left))
    return joined.select(
        *[F.when(clean, whole).otherwise(F.array_join(left, "\n")).alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns],
        n.cast("long").alias(lines_col),
        gone.cast("long").alias(removed_col),
    )
