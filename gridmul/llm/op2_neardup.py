"""N-gram Jaccard join by an LSH forest over MinHash signatures, with exact verification.

Texts become sets of hashed five-word shingles; equal sets collapse to one representative, a node. Each of TREES tries holds a
node's label, MAX_DEPTH MinHash values long, as the keys of its prefixes; the trie's paths that two or more nodes share are
written in sorted order. Matching begins at full depth and shortens the prefix step by step: after each step the matches are
verified, and a pair of similarity s is one of 1 / P(s) that exist, P(s) = 1 - (1 - s^depth)^TREES being its chance to match, so
the verified pairs tell the recall reached. It ends at TARGET_RECALL, or at the depth that guarantees it for any pair at the
threshold. So few close copies cost few candidates, and pairs near the threshold are still met. What is lost is at most the
rest to the target recall, of pairs near the threshold: 0.07% of those at 0.8 exactly, fewer above.

Nodes under one prefix form a star with a centre, its least node. Every member is compared with the centre by the full texts, and
keeps its size and the shingles in which the two differ. Two members' overlap follows from these differences alone:
|a xor b| = |(a xor c) xor (b xor c)|. Members so near to their centre that any two of them are similar are linked by a sum, without
a row for a pair; the others are dealt to blocks, pairs of blocks are tasks, and a task gives one row for each member. A pair that
shares several centres counts at the least.

Classes are the connected components of the links. Nothing unbounded is collected, and there is no cap on buckets.

Defined cases: null text is empty text; a text without words has no shingles, resembles nothing and is a class of its own;
one with one to four words has its whole word sequence as its only shingle; very long texts are read whole; rows that repeat are
copies of each other; rows are told apart by their sets, so rows of one doc_id (or of none, null) with different texts each keep
their own links; a class goes by its least doc_id that is not null, and by null if it has none; an empty table gives an empty
result; extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

import re

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridmul.llm.common import few_files, map_rows, materialise, text_of

WORDS = 5
THRESHOLD = 0.8
TREES = 24
MAX_DEPTH = 8
TARGET_RECALL = 0.999
#: Members of a star that one block holds.
BLOCK = 1024
#: Members of a star that are compared with one copy of the centre's text.
SPLIT = 4096
#: Parts that the members of a star are dealt to where they meet its size.
SALTS = 8
SEED = 20_011

WORD = re.compile(r"\w+")


def chance(similarity: float, depth: int, trees: int = TREES) -> float:
    """Of a pair to share the prefix of so many values in some trie."""
    return 1 - (1 - similarity**depth) ** trees


def least_depth(threshold: float = THRESHOLD, trees: int = TREES, depth: int = MAX_DEPTH, recall: float = TARGET_RECALL) -> int:
    """The longest prefix, at most `depth`, under which any pair at the threshold is met with the target recall."""
    while depth > 1 and chance(threshold, depth, trees) < recall:
        depth -= 1
    return depth


class _Hashes(dict):
    """Word to 64-bit hash; forgets all when large."""

    def __missing__(self, word: str) -> int:
        if len(self) > 400_000:
            self.clear()
        self[word] = value = xxhash.xxh3_64_intdigest(word.encode("utf-8", "surrogatepass"))
        return value


_MIX = np.array([0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], np.uint64)


def shingles(text: str, hashes: dict, n: int = WORDS) -> np.ndarray:
    """Sorted distinct hashes of the text's n-word shingles (words lower-cased, other characters dropped)."""
    words = WORD.findall(text.lower())
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
    n = min(n, len(h))
    with np.errstate(over="ignore"):
        out = np.zeros(len(h) - n + 1, np.uint64)
        for i in range(n):
            out = (out ^ (h[i : len(h) - n + 1 + i] * _MIX[i % len(_MIX)])) * np.uint64(0xFF51AFD7ED558CCD)
            out ^= out >> np.uint64(32)
    return np.unique(out)


def coefficients(count: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(SEED)
    return rng.integers(1, 1 << 63, count, np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 1 << 63, count, np.uint64)


def signature(items: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        out = np.full(len(a), np.iinfo(np.uint64).max, np.uint64)
        for at in range(0, len(items), 256):  # small blocks stay in cache
            np.minimum(out, (items[at : at + 256, None] * a + b).min(axis=0), out=out)
    return out


def signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def _text_key(text_col: str) -> list:
    """128 bits of the text, by which a row finds its text again."""
    return [F.xxhash64(text_of(text_col)).alias("t1"), F.xxhash64(F.lit(1), text_of(text_col)).alias("t2")]


def sketches(docs: DataFrame, id_col: str, text_col: str, words: int, trees: int, depths: range) -> DataFrame:
    """(doc_id, t1, t2, print, labels): the text's key, the set's fingerprint, for each trie the keys of its prefixes of these depths."""

    def rows(source):
        a, b = coefficients(trees * depths[-1])
        hashes = _Hashes()
        for key, t1, t2, text in source:
            items = shingles(text, hashes, words)
            if not len(items):
                yield key, t1, t2, None, []
                continue
            label = signature(items, a, b).reshape(trees, depths[-1])
            keys = [[signed(xxhash.xxh3_64_intdigest(row[:d].tobytes(), seed=t)) for d in depths] for t, row in enumerate(label)]
            yield key, t1, t2, xxhash.xxh3_128_digest(items.tobytes()), keys

    return map_rows(docs, [F.col(id_col).cast("long"), *_text_key(text_col), text_of(text_col)], "doc_id long, t1 long, t2 long, print binary, labels array<array<long>>", rows)


def tries(nodes: DataFrame) -> DataFrame:
    """(node, path): the tries' labels as keys from the shortest prefix on, in sorted order; those alone under it meet nobody."""
    paths = nodes.select("node", F.explode("labels").alias("path")).withColumn("root", F.col("path")[0])
    met = paths.groupBy("root").agg(F.count("*").alias("n")).where("n > 1").select("root")
    return materialise(paths.join(met, "root").select("node", "path").sortWithinPartitions("path"), "tries", narrow=True)


def stars_at(forest: DataFrame, step: int) -> DataFrame:
    """(centre, member, size): the nodes under each prefix of that step, by the least of them; sizes count distinct members."""
    paths = forest.select("node", F.col("path")[step].alias("key"))
    centres = paths.groupBy("key").agg(F.min("node").alias("centre"), F.count("*").alias("n")).where("n > 1")
    stars = materialise(paths.join(centres.select("key", "centre"), "key").select("centre", F.col("node").alias("member")).distinct(), "stars", narrow=True)
    sizes = stars.groupBy("centre").agg(F.count("*").alias("size")).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return stars.withColumn("salt", F.pmod(F.xxhash64("member"), F.lit(SALTS)).cast("int")).join(sizes, ["centre", "salt"]).drop("salt")


def _packed(x: np.ndarray) -> bytes:
    return x.tobytes()


def compare_with_centre(stars: DataFrame, texts: DataFrame, words: int) -> DataFrame:
    """(centre, member, size, n, differ, similarity): each member's shingles against its centre's. texts: (node, text)."""
    parts = F.ceil(F.col("size") / SPLIT).cast("int")
    dealt = stars.withColumn("part", F.pmod(F.xxhash64("member"), parts).cast("int"))
    with_m = dealt.join(texts.select(F.col("node").alias("member"), F.col("text").alias("text_m")), "member")
    # as many copies of the centre's text as its star has parts
    centres = stars.where("centre = member").select("centre", F.explode(F.sequence(F.lit(0), parts - 1)).alias("part"))
    with_c = with_m.join(centres.join(texts.select(F.col("node").alias("centre"), F.col("text").alias("text_c")), "centre"), ["centre", "part"])

    def rows(source):
        hashes = _Hashes()
        last, items_c = None, None
        for centre, member, size, text_c, text_m in source:
            if centre != last:
                last, items_c = centre, shingles(text_c, hashes, words)
            items = shingles(text_m, hashes, words)
            differ = np.setxor1d(items, items_c, assume_unique=True)
            both = (len(items) + len(items_c) - len(differ)) / 2
            yield centre, member, size, len(items), _packed(differ), both / (both + len(differ))

    return map_rows(with_c, [F.col(c) for c in ("centre", "member", "size", "text_c", "text_m")], "centre long, member long, size long, n long, differ binary, similarity double", rows)


def reached(compared: DataFrame, depth: int, trees: int, threshold: float) -> float:
    """The share of all similar pairs that prefixes of this depth meet, as the verified pairs tell; 0 where there is none."""
    similar = compared.where((F.col("centre") != F.col("member")) & (F.col("similarity") >= threshold))
    met = 1 - F.pow(1 - F.pow("similarity", F.lit(depth)), F.lit(trees))
    n, total = similar.agg(F.count("*"), F.sum(1 / met)).first()
    return n / total if n else 0.0


def overlaps(sets: list[np.ndarray], others: list[np.ndarray] | None = None) -> np.ndarray:
    """Sizes of all pairwise intersections of sorted distinct arrays (between the two lists, if two are given)."""
    both = sets + (others or [])
    n, m = len(sets), len(both)
    out = np.zeros((n, m - n) if others is not None else (n, n), np.float32)
    if not both or not sum(map(len, both)):
        return out
    items = np.concatenate(both)
    owner = np.repeat(np.arange(m), [len(s) for s in both])
    order = np.argsort(items, kind="stable")
    items, owner = items[order], owner[order]
    starts = np.flatnonzero(np.concatenate(([True], items[1:] != items[:-1])))
    sizes = np.diff(np.concatenate((starts, [len(items)])))
    # items of a single set meet nothing
    column = np.repeat(np.arange(len(starts)), sizes)
    shared = sizes[column] > 1
    owner, column = owner[shared], column[shared]
    if not len(column):
        return out
    column = np.cumsum(np.concatenate(([0], (column[1:] != column[:-1]).astype(np.int64))))
    slab = 4096
    for lo in range(0, int(column[-1]) + 1, slab):
        i, j = np.searchsorted(column, (lo, lo + slab))
        hit = np.zeros((m, min(slab, int(column[-1]) + 1 - lo)), np.float32)
        hit[owner[i:j], column[i:j] - lo] = 1
        out += hit[:n] @ (hit[n:] if others is not None else hit).T
    return out


def link_block(left: list[tuple], right: list[tuple] | None, centre: int, threshold: float) -> list[tuple[int, int, int]]:
    """(member, linked copies, a linked neighbour) of the pairs between two blocks, or within one (right is None).

    A member is (id, n, difference from the centre, its centres, copies)."""
    rights = left if right is None else right
    dl, dr = [np.frombuffer(x[2], np.uint64) for x in left], [np.frombuffer(x[2], np.uint64) for x in rights]
    both = overlaps(dl, None if right is None else dr)
    nl, nr = np.array([x[1] for x in left], float), np.array([x[1] for x in rights], float)
    apart = np.array([len(d) for d in dl], float)[:, None] + np.array([len(d) for d in dr], float) - 2 * both
    common = (nl[:, None] + nr - apart) / 2
    linked = common >= threshold * (nl[:, None] + nr - common) - 1e-9
    if right is None:
        np.fill_diagonal(linked, False)
    # a pair that shares a smaller centre counts there
    smaller: dict[int, int] = {}
    rows_of = []
    for side in (left, rights):
        rows_of.append([[smaller.setdefault(c, len(smaller)) for c in x[3] if c < centre] for x in side])
    if smaller and any(rows_of[0]) and any(rows_of[1]):
        marks = [np.zeros((len(side), len(smaller)), np.float32) for side in (left, rights)]
        for mark, rows in zip(marks, rows_of):
            for i, cs in enumerate(rows):
                mark[i, cs] = 1
        linked &= marks[0] @ marks[1].T == 0
    wl, wr = np.array([x[4] for x in left], np.int64), np.array([x[4] for x in rights], np.int64)
    ids_l, ids_r = np.array([x[0] for x in left], np.int64), np.array([x[0] for x in rights], np.int64)
    least_l, least_r = _least(linked, ids_l, ids_r)
    sums = linked @ wr
    out = [(int(ids_l[i]), int(sums[i]), int(least_l[i])) for i in np.flatnonzero(linked.any(axis=1)).tolist()]
    if right is not None:
        back = linked.T @ wl
        out += [(int(ids_r[j]), int(back[j]), int(least_r[j])) for j in np.flatnonzero(linked.any(axis=0)).tolist()]
    return out


def _least(linked: np.ndarray, ids_l: np.ndarray, ids_r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The least id that each row (column) reaches over links within the block."""
    far = np.iinfo(np.int64).max
    low_l, low_r = ids_l.copy(), ids_r.copy()
    while True:
        new_r = np.minimum(low_r, np.where(linked, low_l[:, None], far).min(axis=0, initial=far))
        new_l = np.minimum(low_l, np.where(linked, new_r, far).min(axis=1, initial=far))
        if (new_l == low_l).all() and (new_r == low_r).all():
            return low_l, low_r
        low_l, low_r = new_l, new_r


def sure_links(members: DataFrame, threshold: float) -> tuple[DataFrame, DataFrame]:
    """(links, members with `sure`): a member is sure where its star's centre is the least of its centres and it differs from it in
    so few shingles that any two such members are similar: |a xor b| <= d(a) + d(b) <= (n(a) + n(b)) (1 - t) / (1 + t)."""
    bound = (1 - threshold) / (1 + threshold)
    sure = (F.col("centre") == F.col("centres")[0]) & (F.octet_length("differ") / 8 <= F.col("n") * bound)
    marked = members.withColumn("sure", sure)
    salted = marked.where("sure").select("centre", "member", "copies", F.pmod(F.xxhash64("member"), F.lit(SALTS)).cast("int").alias("salt"))
    sums = salted.groupBy("centre").agg(F.sum("copies").alias("all"), F.min("member").alias("least"), F.count("*").alias("n")).where("n > 1").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    links = salted.join(sums, ["centre", "salt"]).select(F.col("member").alias("doc"), (F.col("all") - F.col("copies")).alias("copies"), F.col("least").alias("neighbour"))
    return links, marked


def block_links(members: DataFrame, threshold: float, block: int) -> DataFrame:
    """(doc, copies, neighbour): what each star adds to a member's links. A neighbour is in the same class."""
    sure, marked = sure_links(members, threshold)
    # blocks of sure members come first; two of them need no task
    per_star = marked.groupBy("centre").agg(F.count(F.when(F.col("sure"), 1)).alias("n_sure"), F.count(F.when(~F.col("sure"), 1)).alias("n_far")).where("n_far > 0")
    blocks = per_star.select("centre", F.ceil(F.col("n_sure") / block).cast("int").alias("b_sure"), F.ceil(F.col("n_far") / block).cast("int").alias("b_far")).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    sized = marked.withColumn("salt", F.pmod(F.xxhash64("member"), F.lit(SALTS)).cast("int")).join(blocks, ["centre", "salt"])
    own = F.when(F.col("sure"), F.expr("pmod(xxhash64(member, 1), b_sure)")).otherwise(F.expr("b_sure + pmod(xxhash64(member, 1), b_far)")).cast("int")
    others = F.sequence(F.when(F.col("sure"), F.col("b_sure")).otherwise(F.lit(0)), F.col("b_sure") + F.col("b_far") - 1)
    dealt = sized.withColumn("own", own).withColumn("other", F.explode(others)).withColumn("lo", F.least("own", "other")).withColumn("hi", F.greatest("own", "other"))

    def rows(source):
        def task(key, rows):
            centre, lo, hi = key
            left = [r for own, r in rows if own == lo]
            if lo == hi:
                yield from link_block(left, None, centre, threshold)
            else:
                right = [r for own, r in rows if own == hi]
                if left and right:
                    yield from link_block(left, right, centre, threshold)

        key, held = None, []
        for centre, lo, hi, own, *member in source:
            if (centre, lo, hi) != key:
                if held:
                    yield from task(key, held)
                key, held = (centre, lo, hi), []
            held.append((own, tuple(member)))
        if held:
            yield from task(key, held)

    # rows of one task follow each other within a partition; only one pair of blocks is held at a time
    spread = dealt.repartition("centre", "lo", "hi").sortWithinPartitions("centre", "lo", "hi")
    far = map_rows(spread, [F.col(c) for c in ("centre", "lo", "hi", "own", "member", "n", "differ", "centres", "copies")], "doc long, copies long, neighbour long", rows)
    return sure.unionByName(far)


def components(edges: DataFrame, label: str = "components") -> DataFrame:
    """(node, least) for every node of the edges (u, v): least labels spread along edges, with labels' own labels taken over
    (pointer jumping), until nothing changes. Each round is written to cut lineage."""
    both = materialise(edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))).where("u <> v").distinct(), f"{label}-edges", narrow=True)
    least = materialise(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("least")).withColumnRenamed("u", "node"), label, narrow=True)
    while True:
        near = both.join(least, both.v == least.node).groupBy("u").agg(F.min("least").alias("near"))
        step = least.join(near, least.node == near.u).select("node", F.col("least").alias("before"), F.least("least", "near").alias("mid"))
        jump = least.select(F.col("node").alias("n2"), F.col("least").alias("jumped"))
        after = materialise(step.join(jump, step.mid == jump.n2, "left").select("node", "before", F.least("mid", F.coalesce("jumped", "mid")).alias("least")), label, narrow=True)
        least = after.select("node", "least")
        if after.where("least <> before").isEmpty():
            return least


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, words: int = WORDS, trees: int = TREES, max_depth: int = MAX_DEPTH, recall: float = TARGET_RECALL, block: int = BLOCK) -> DataFrame:
    """(doc_id, class_id, n_links): the least doc_id of the class; how many other rows the row is linked to."""
    depths = range(least_depth(threshold, trees, max_depth, recall), max_depth + 1)
    sketched = materialise(sketches(docs, id_col, text_col, words, trees, depths), "sketches")
    # equal sets: one node, the number of its rows, the row whose text stands for all
    one = F.min(F.struct(F.col("doc_id"), F.col("t1"), F.col("t2"), F.col("labels"))).alias("one")
    nodes = sketched.where("print IS NOT NULL").groupBy("print").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies"), one)
    nodes = materialise(nodes.select("print", "rep", "copies", "one.*").withColumn("node", F.monotonically_increasing_id()), "nodes")
    forest = tries(nodes)
    # only the texts of nodes that can meet another one travel
    wanted = forest.select("node").distinct().join(nodes.select("node", F.col("doc_id").alias("one_id"), F.col("t1"), F.col("t2")), "node")
    rows = docs.select(F.col(id_col).cast("long").alias("id"), *_text_key(text_col), text_of(text_col).alias("text"))
    texts = materialise(few_files(rows.join(wanted, (rows.t1 == wanted.t1) & (rows.t2 == wanted.t2) & rows.id.eqNullSafe(wanted.one_id)).groupBy("node").agg(F.min("text").alias("text"))), "texts")
    for step in reversed(range(len(depths))):
        stars = materialise(stars_at(forest, step), "stars", narrow=True)
        compared = materialise(few_files(compare_with_centre(stars, texts, words)), "compared")
        if step and reached(compared, depths[step], trees, threshold) >= recall:
            break
    centres = stars.groupBy("member").agg(F.sort_array(F.collect_set("centre")).alias("centres"))  # at most one for each trie
    members = compared.join(centres.join(nodes.select(F.col("node").alias("member"), "copies"), "member"), "member")
    links = materialise(block_links(members, threshold, block), "links", narrow=True)
    counts = links.groupBy("doc").agg(F.sum("copies").alias("linked"))
    parts = components(links.select(F.col("doc").alias("u"), F.col("neighbour").alias("v"))).withColumnRenamed("least", "class")
    of_node = nodes.select("print", "node", "rep", "copies").join(counts, F.col("node") == F.col("doc"), "left").join(parts.withColumnRenamed("node", "part"), F.col("node") == F.col("part"), "left")
    of_node = materialise(of_node.select("print", "rep", F.coalesce("class", "node").alias("class"), (F.col("copies") - 1 + F.coalesce("linked", F.lit(0))).alias("n_links")), "node-links", narrow=True)
    names = of_node.groupBy("class").agg(F.min("rep").alias("class_id"))
    found = sketched.select("doc_id", "print").join(of_node.join(names, "class").select("print", "class_id", "n_links"), "print", "left")
    return found.select("doc_id", F.when(F.col("n_links").isNull(), F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))
