"""SentencePiece encoding and decoding by a relational lattice.

Texts fall into words that start with the space sign; no piece reaches over a word's start, so words are encoded alone and
every distinct word once. Substrings up to the longest piece are exploded and equi-joined to the piece table, the edges of a
word are grouped and folded: Viterbi over the positions for unigram models, or, for BPE models whose encoding is not the
best-scored path, the merges in the order of their scores.

Two physical forms give the same ids. `lexicon` and `encode_by_lexicon` do all of it in DataFrame functions, with the fold as a
higher-order aggregate, and send a dictionary of encoded words back to the documents; that ships texts and words several times
(figures in the README). `encode` does the same relational steps on columns of numbers within a task, over the distinct words of
the texts it holds, and shuffles nothing.

Words longer than MAX_FOLD code points, or with characters that no piece has (byte fallback), are encoded by the same merges on
a heap, exactly.

Defined cases: null or empty text has no tokens; very long texts are encoded whole; pieces of one score go by their ids; the text's own space signs count as blanks and decode to blanks; repeated rows
are encoded alike; an empty table gives an empty result; extra columns, whatever their names,
are ignored.
"""

from __future__ import annotations

import heapq
import re
from dataclasses import dataclass, fields
from pathlib import Path

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmul.llm.common import map_rows, materialise, small_batches, text_of

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
SPACE = "▁"
#: The borders of a word of up to so many code points fit one 64-bit mask.
MAX_FOLD = 61
#: Neighbouring ids that share a dictionary.
CHUNK_IDS = 8192
BUCKETS = 256
#: Distinct words that a task holds before it hands them on.
HELD_WORDS = 1_000_000
_ENTRY, _FIELD = "\x02", "\x01"
WORDS = re.compile(f"{SPACE}+[^{SPACE}]*")


@dataclass(frozen=True)
class Model:
    pieces: tuple[tuple[str, float, int], ...]  # (piece, score, id) of ordinary pieces
    bytes_at: int | None  # id of byte 0
    unknown: int
    kind: str  # unigram or bpe
    by_id: tuple[str, ...]
    longest: int

    def values(self) -> tuple:
        """Plain values for a broadcast: workers need no class of this package to read it."""
        return tuple(getattr(self, f.name) for f in fields(self))

    @property
    def score_of(self) -> dict[int, float]:
        return {i: s for _, s, i in self.pieces}

    @property
    def by_rank(self) -> list[int]:
        """Ids of ordinary pieces, the best score first."""
        return [i for _, _, i in sorted(self.pieces, key=lambda p: (-p[1], p[2]))]


def _fields(data: bytes):
    """(number, value) of the fields of one protocol-buffer message; groups do not occur."""
    at = 0

    def varint() -> int:
        nonlocal at
        out = shift = 0
        while True:
            b = data[at]
            at += 1
            out |= (b & 127) << shift
            shift += 7
            if b < 128:
                return out

    while at < len(data):
        key = varint()
        if key & 7 == 0:
            yield key >> 3, varint()
        else:
            size = {1: 8, 5: 4}.get(key & 7) or varint()
            yield key >> 3, data[at : at + size]
            at += size


def load_model(path: str = MODEL) -> Model:
    """The piece table of a model file with identity normalisation and a space put before the text."""
    import struct

    pieces, by_id, bytes_at, unknown, kind = [], [], None, 0, "unigram"
    for number, value in _fields(Path(path).read_bytes()):
        if number == 1:
            f = dict(_fields(value))
            piece, what, i = f[1].decode(), f.get(3, 1), len(by_id)
            by_id.append(piece)
            if what == 1:
                pieces.append((piece, struct.unpack("<f", f[2])[0] if 2 in f else 0.0, i))
            elif what == 6 and bytes_at is None:
                bytes_at = i
            elif what == 2:
                unknown = i
        elif number == 2:
            kind = {1: "unigram", 2: "bpe"}.get(dict(_fields(value)).get(3, 1), "other")
        elif number == 3:
            f = dict(_fields(value))
            if f.get(2) or f.get(4, 1) or not f.get(3, 1):
                raise ValueError("only models with identity normalisation, a space before the text and all blanks kept")
    if kind == "other":
        raise ValueError("only unigram and BPE models")
    return Model(tuple(pieces), bytes_at, unknown, kind, tuple(by_id), max(len(p[0]) for p in pieces))


def split_words(text: str) -> list[str]:
    return WORDS.findall(SPACE + text.replace(" ", SPACE)) if text else []


class Encoder:
    """One word at a time, on a heap of merges: for words that the fold does not take."""

    def __init__(self, model: Model):
        self.model = model
        self.score = {p: (s, i) for p, s, i in model.pieces}

    def ids(self, token: str) -> list[int]:
        if token in self.score:
            return [self.score[token][1]]
        if self.model.bytes_at is None:
            return [self.model.unknown]
        return [self.model.bytes_at + b for b in token.encode("utf-8", "surrogatepass")]

    def encode(self, word: str) -> list[int]:
        if self.model.kind == "unigram":
            return self._best_path(word)
        n = len(word)
        text, left, right = list(word), list(range(-1, n - 1)), list(range(1, n + 1))
        heap: list[tuple[float, int, int, str]] = []

        def offer(i: int) -> None:
            j = right[i]
            if i >= 0 and j < n and (both := text[i] + text[j]) in self.score:
                heapq.heappush(heap, (-self.score[both][0], i, j, both))

        for i in range(n - 1):
            offer(i)
        while heap:
            _, i, j, both = heapq.heappop(heap)
            if not text[i] or right[i] != j or text[i] + text[j] != both:
                continue
            text[i], text[j] = both, ""
            right[i] = right[j]
            if right[i] < n:
                left[right[i]] = i
            offer(i)
            if left[i] >= 0:
                offer(left[i])
        return [x for t in text if t for x in self.ids(t)]

    def _best_path(self, word: str) -> list[int]:
        n = len(word)
        low = min(s for s, _ in self.score.values()) - 10
        best: list[tuple[float, int]] = [(0.0, 0)] + [(float("-inf"), 0)] * n
        for e in range(1, n + 1):
            for s in range(max(0, e - self.model.longest), e):
                found = self.score.get(word[s:e])
                if found or e - s == 1:
                    best[e] = max(best[e], (best[s][0] + (found[0] if found else low), s), key=lambda x: x[0])
        out, e = [], n
        while e:
            s = best[e][1]
            out.append(self.ids(word[s:e]))
            e = s
        return [x for ids in reversed(out) for x in ids]


def piece_table(spark: SparkSession, model: Model) -> DataFrame:
    """(sub, rank): as many rows as the model has pieces, whatever the input. Rank 0 is the best score, ties by id."""
    import pandas as pd

    return spark.createDataFrame(pd.DataFrame({"sub": [model.by_id[i] for i in model.by_rank], "rank": range(len(model.by_rank))}), "sub string, rank long")


#: An edge is one number, rank * 4096 + start * 64 + end, so that edges sort by rank and then place. As a struct it has bit masks
#: of its two borders and of those inside it; bit i stands for the border before code point i.
_OPEN = """transform(edges, x -> named_struct('code', x,
    'ends', shiftleft(1L, CAST((x >> 6) & 63 AS INT)) | shiftleft(1L, CAST(x & 63 AS INT)),
    'inner', (shiftleft(1L, CAST(x & 63 AS INT)) - 1) & ~(shiftleft(1L, CAST((x >> 6) & 63 AS INT) + 1) - 1)))"""


def lexicon(words: DataFrame, model: Model) -> DataFrame:
    """(bucket, word, ranks) for distinct (bucket, word), dealt by bucket: the ranks of the word's pieces in order; null where
    a character is no piece, so that the word needs the byte fallback."""
    starts = words.withColumn("n", F.length("word")).select("*", F.explode(F.expr("sequence(0, n - 1)")).alias("s"))
    cut = starts.select("*", F.explode(F.expr(f"sequence(1, least({model.longest}, n - s))")).alias("l")).select("bucket", "word", "n", "s", "l", F.expr("substring(word, s + 1, l)").alias("sub"))
    # the piece table is broadcast: its size is the model's, about 1 MB
    edges = cut.join(F.broadcast(piece_table(words.sparkSession, model)), "sub").select("bucket", "word", "n", F.expr("rank * 4096 + s * 64 + s + l").alias("edge"))
    grouped = edges.groupBy("bucket", "word", "n").agg(F.sort_array(F.collect_list("edge")).alias("edges")).withColumn("edges", F.expr(_OPEN))
    if model.kind == "bpe":
        # the best-ranked edge that joins exactly two tokens is merged, again and again; each merge takes one inner border away
        joins = grouped.withColumn("joins", F.expr("filter(edges, x -> x.inner <> 0)"))
        merged = joins.withColumn("borders", F.expr("""
            IF(size(joins) = 0, shiftleft(1L, n + 1) - 1, aggregate(sequence(1, least(n - 1, size(joins))), shiftleft(1L, n + 1) - 1,
              (b, i) -> coalesce(b & ~get(filter(joins, x -> (b & x.ends) = x.ends AND bit_count(b & x.inner) = 1), 0).inner, b)))"""))
        folded = merged.withColumn("path", F.expr("array_sort(transform(filter(edges, x -> (borders & x.ends) = x.ends AND (borders & x.inner) = 0), x -> named_struct('at', x.code & 4095, 'rank', x.code >> 12)))"))
    else:
        scores = F.lit([model.score_of[i] for i in model.by_rank])
        folded = grouped.withColumn("scored", F.transform("edges", lambda x: F.struct((x["code"].bitwiseAND(4095)).alias("at"), F.shiftright(x["code"], 12).alias("rank"), F.get(scores, F.shiftright(x["code"], 12).cast("int")).alias("score"))))
        empty = "CAST(array() AS array<struct<at:bigint,rank:bigint>>)"
        # Viterbi: the best path to each place from the best paths to the places before it
        folded = folded.withColumn("path", F.expr(f"""
            element_at(aggregate(sequence(1, n), array(named_struct('score', 0D, 'path', {empty})),
              (best, to) -> array_append(best, aggregate(filter(scored, x -> (x.at & 63) = to), named_struct('score', CAST('-Infinity' AS DOUBLE), 'path', {empty}),
                (m, x) -> IF(get(best, CAST(shiftright(x.at, 6) AS INT)).score + x.score > m.score,
                  named_struct('score', get(best, CAST(shiftright(x.at, 6) AS INT)).score + x.score, 'path', array_append(get(best, CAST(shiftright(x.at, 6) AS INT)).path, named_struct('at', x.at, 'rank', x.rank))), m)))), -1).path"""))
    whole = F.expr("aggregate(path, 0L, (a, x) -> a + (x.at & 63) - (x.at >> 6)) = n")
    return folded.select("bucket", "word", F.when(whole, F.expr("transform(path, x -> x.rank)")).alias("ranks"))


def _chunk(key):
    return F.coalesce(F.floor(key / CHUNK_IDS), -1 - F.pmod(F.xxhash64("text"), F.lit(64)))


def chunk_words(texts: DataFrame) -> DataFrame:
    """(bucket, chunk, words): each task's distinct words of a chunk, by bucket, as one string a row."""

    def rows(source):
        held: dict[int, set[str]] = {}
        size = 0

        def hand_on():
            for chunk, words in held.items():
                by: dict[int, list[str]] = {}
                for w in words:
                    if len(w) <= MAX_FOLD and _ENTRY not in w and _FIELD not in w:
                        by.setdefault(xxhash.xxh3_64_intdigest(w.encode("utf-8", "surrogatepass")) % BUCKETS, []).append(w)
                for b, ws in by.items():
                    yield b, chunk, _ENTRY.join(sorted(ws))
            held.clear()

        for chunk, text in source:
            words = held.setdefault(chunk, set())
            before = len(words)
            words.update(split_words(text))
            size += len(words) - before
            if size > HELD_WORDS:
                yield from hand_on()
                size = 0
        yield from hand_on()

    return map_rows(texts, [F.col("chunk"), F.col("text")], "bucket int, chunk long, words string", rows)


def encode_by_lexicon(docs: DataFrame, model_path: str = MODEL, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids, n_tokens, n_words, decoded_equal): token ids of every row's whole text, and whether they decode to it."""
    model = load_model(model_path)
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text")).withColumn("chunk", _chunk(F.col("doc_id")).cast("long"))
    dealt = materialise(chunk_words(texts), "words").repartition("bucket")
    exploded = dealt.select("bucket", "chunk", F.explode(F.split("words", _ENTRY, -1)).alias("word"))
    known = lexicon(exploded.select("bucket", "word").distinct(), model)
    # both sides are dealt by bucket already; a chunk's entries of a bucket leave as one string
    entry = F.when(F.col("ranks").isNotNull(), F.concat_ws(_FIELD, "word", F.array_join("ranks", " ")))
    packed = exploded.join(known.hint("shuffle_hash"), ["bucket", "word"]).groupBy("bucket", "chunk").agg(F.array_join(F.collect_list(entry), _ENTRY).alias("entries"))
    rows_in = packed.select("chunk", F.lit(0).alias("kind"), F.lit(None).cast("long").alias("doc_id"), F.col("entries").alias("text")).unionByName(texts.select("chunk", F.lit(1).alias("kind"), "doc_id", "text"))
    together = rows_in.repartition("chunk").sortWithinPartitions("chunk", "kind")
    shared = docs.sparkSession.sparkContext.broadcast(model.values())  # of the model's size

    def rows(source):
        held = Model(*shared.value)
        encoder, decoder, by_rank = Encoder(held), Decoder(held), held.by_rank
        now, book = None, {}
        for chunk, kind, key, text in source:
            if chunk != now:
                now, book = chunk, {}
            if not kind:
                for e in text.split(_ENTRY):
                    w, _, ranks = e.rpartition(_FIELD)
                    if w:
                        book[w] = [by_rank[int(r)] for r in ranks.split(" ")]
                continue
            words = split_words(text)
            ids: list[int] = []
            for w in words:
                got = book.get(w)
                if got is None:
                    got = book[w] = encoder.encode(w)
                ids += got
            yield key, ids, len(ids), len(words), decoder.decode(ids) == text.replace(SPACE, " ")

    return map_rows(together, [F.col(c) for c in ("chunk", "kind", "doc_id", "text")], "doc_id long, ids array<int>, n_tokens long, n_words long, decoded_equal boolean", rows)


class Lattice:
    """Encodes many distinct words at once: explode, join, group and fold on columns of numbers."""

    BLOCK_CHARS = 400_000
    _BASE = np.uint64(0x9E3779B97F4A7C15 | 1)

    def __init__(self, model: Model):
        self.model = model
        self.encoder = Encoder(model)
        self.decoder = Decoder(model)
        self.powers = self._powers(self._BASE, model.longest)
        by_rank = model.by_rank
        self.ids = np.array(by_rank, np.int32)
        # the piece table as a hash table with open addressing: key (the hash of the piece) to rank
        self.bits = max(4, (len(by_rank) * 8).bit_length())
        self.keys, self.ranks = np.zeros(1 << self.bits, np.uint64), np.full(1 << self.bits, -1, np.int32)
        flat = np.frombuffer("".join(model.by_id[i] for i in by_rank).encode("utf-32-le"), np.uint32)
        ends = np.cumsum([len(model.by_id[i]) for i in by_rank])
        prefix = self._prefix(flat)
        for rank, (a, b) in enumerate(zip([0, *ends[:-1].tolist()], ends.tolist())):
            key = self._hash(prefix, np.array([a]), b - a)
            at = int(self._slot(key)[0])
            while self.ranks[at] >= 0:
                at = (at + 1) % len(self.keys)
            self.keys[at], self.ranks[at] = key[0], rank

    @staticmethod
    def _powers(base: np.uint64, n: int) -> np.ndarray:
        out = np.full(n + 1, base, np.uint64)
        out[0] = 1
        return np.cumprod(out, dtype=np.uint64)

    def _prefix(self, codes: np.ndarray) -> np.ndarray:
        """Hashes of all prefixes, by a running product that wraps."""
        # h[i + 1] = h[i] * base + code is a scan; over inverse powers it is a plain sum
        inverse = np.uint64(pow(int(self._BASE), -1, 1 << 64))
        n = len(codes)
        back = self._powers(inverse, n)
        out = np.zeros(n + 1, np.uint64)
        np.cumsum((codes.astype(np.uint64) + np.uint64(1)) * back[1:], out=out[1:])
        return out * self._powers(self._BASE, n)

    def _hash(self, prefix: np.ndarray, at: np.ndarray, length: int) -> np.ndarray:
        return (prefix[at + length] - prefix[at] * self.powers[length]) * np.uint64(0xD6E8FEB86659FD93) + np.uint64(length)

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key ^ (key >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) >> np.uint64(64 - self.bits)).astype(np.int64)

    def _join(self, key: np.ndarray) -> np.ndarray:
        """Rank of each key, -1 where it is no piece."""
        slot = self._slot(key)
        out = np.where(self.keys[slot] == key, self.ranks[slot], -1)
        open_ = np.flatnonzero((out < 0) & (self.ranks[slot] >= 0))
        while len(open_):
            slot[open_] = (slot[open_] + 1) % len(self.keys)
            s = slot[open_]
            hit = (self.keys[s] == key[open_]) & (self.ranks[s] >= 0)
            out[open_[hit]] = self.ranks[s[hit]]
            open_ = open_[~hit & (self.ranks[s] >= 0)]
        return out

    def encode(self, words: list[str]) -> dict[str, bytes]:
        """Word to its ids as 32-bit numbers."""
        out: dict[str, bytes] = {}
        block: list[str] = []
        size = 0
        for w in words:
            if len(w) > MAX_FOLD or self.model.kind != "bpe":
                out[w] = np.array(self.encoder.encode(w), np.int32).tobytes()
                continue
            block.append(w)
            size += len(w)
            if size >= self.BLOCK_CHARS:
                self._block(block, out)
                block, size = [], 0
        if block:
            self._block(block, out)
        return out

    def _block(self, words: list[str], out: dict[str, bytes]) -> None:
        codes = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)
        sizes = np.array([len(w) for w in words])
        ends = np.cumsum(sizes)
        begins = ends - sizes
        n = len(codes)
        left = np.repeat(ends, sizes) - np.arange(n)  # code points to the word's end
        with np.errstate(over="ignore"):
            prefix = self._prefix(codes)
            # explode the substrings of each length and join them to the pieces; ranks[length, start]
            ranks = np.full((self.model.longest + 1, n), -1, np.int32)
            for length in range(1, self.model.longest + 1):
                at = np.flatnonzero(left >= length)
                if not len(at):
                    break
                ranks[length, at] = self._join(self._hash(prefix, at, length))
        start, length, word = np.arange(n, dtype=np.int32), np.ones(n, np.int32), np.repeat(np.arange(len(words), dtype=np.int32), sizes)
        offset = start - np.repeat(begins, sizes).astype(np.int32)
        done: list[tuple[np.ndarray, np.ndarray]] = []
        none = np.iinfo(np.int32).max  # ranks times 64 stay below: a piece table has far fewer than 2^25 rows
        flat, most = ranks.ravel(), self.model.longest
        key = np.full(n, none, np.int32)

        def pair_keys(i: np.ndarray) -> np.ndarray:
            """Keys of the pairs (i, i + 1): rank, then place."""
            out = np.full(len(i), none, np.int32)
            i_, j = i[i + 1 < len(start)], i[i + 1 < len(start)] + 1
            both = length[i_] + length[j]
            fits = np.flatnonzero((word[i_] == word[j]) & (both <= most))
            found = flat[both[fits].astype(np.int64) * n + start[i_[fits]]]
            out[fits] = np.where(found >= 0, found * 64 + offset[i_[fits]], none)
            return out

        key = pair_keys(np.arange(n))
        while len(start):
            # every word merges its best-ranked pair, the leftmost of equals; words without one are finished
            heads = np.flatnonzero(np.concatenate(([True], word[1:] != word[:-1])))
            least = np.minimum.reduceat(key, heads)
            best = np.repeat(least, np.diff(np.append(heads, len(word))))
            over = best == none
            if over.any():
                done.append((start[over], length[over]))
            at = np.flatnonzero((key == best) & ~over)
            length[at] += length[at + 1]
            keep = ~over
            keep[at + 1] = False
            place = np.cumsum(keep) - 1
            start, length, word, offset, key = start[keep], length[keep], word[keep], offset[keep], key[keep]
            # only the merged token's pair and the one before it are new
            merged = place[at]
            key[merged] = pair_keys(merged)
            before = merged[merged > 0] - 1
            key[before] = pair_keys(before)
        start, length = (np.concatenate(x) for x in zip(*done))
        order = np.argsort(start, kind="stable")
        start, length = start[order], length[order]
        got = ranks[length, start]
        ids = np.where(got >= 0, self.ids[np.maximum(got, 0)], -1).astype(np.int32)
        # characters that are no piece stand for their bytes, or for the unknown piece
        rare = np.flatnonzero(got < 0)
        wide = np.ones(len(ids), np.int64)
        kinds, which = np.unique(codes[start[rare]], return_inverse=True)
        spelled = [self.encoder.ids(chr(c)) for c in kinds.tolist()]
        wide[rare] = np.array([len(x) for x in spelled], np.int64)[which] if len(rare) else 1
        first = np.cumsum(wide) - wide
        ids = np.repeat(ids, wide)
        for k, x in enumerate(spelled):
            at = first[rare[which == k]]
            for j, i in enumerate(x):
                ids[at + j] = i
        cuts = np.append(first, len(ids))[np.searchsorted(start, ends)]
        raw = ids.tobytes()
        at = 0
        for w, cut in zip(words, (4 * cuts).tolist()):
            out[w] = raw[at:cut]
            at = cut


#: Characters of texts, and distinct words, that a task holds at a time.
HELD_CHARS = 4_000_000
BOOK_WORDS = 600_000


def encode(docs: DataFrame, model_path: str = MODEL, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids, n_tokens, n_words, decoded_equal): token ids of every row's whole text, and whether they decode to it."""
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(load_model(model_path).values())  # of the model's size
    schema = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32())), ("n_tokens", pa.int64()), ("n_words", pa.int64()), ("decoded_equal", pa.bool_())])

    def run(batches):
        lattice = Lattice(Model(*shared.value))
        book: dict[str, bytes] = {}
        odd: set[str] = set()  # words that decode to something else: with the space sign or broken code points in the text

        def hand_on(held: list[tuple]) -> pa.RecordBatch:
            new = {w for _, words in held for w in words} - book.keys()
            if len(book) + len(new) > BOOK_WORDS:
                book.clear()
                odd.clear()
                new = {w for _, words in held for w in words}
            got = lattice.encode(list(new))
            book.update(got)
            # all new words are decoded together; one by one only where that shows a difference
            if got and lattice.decoder.raw(np.frombuffer(b"".join(got.values()), np.int32).tolist()) != "".join(got).replace(SPACE, " ").encode("utf-8", "surrogatepass"):
                odd.update(w for w, raw in got.items() if lattice.decoder.raw(np.frombuffer(raw, np.int32).tolist()) != w.replace(SPACE, " ").encode("utf-8", "surrogatepass"))
            parts = [b"".join(map(book.__getitem__, words)) for _, words in held]
            sizes = np.array([len(p) // 4 for p in parts], np.int64)
            flat = pa.py_buffer(b"".join(parts))
            values = pa.Array.from_buffers(pa.int32(), int(sizes.sum()), [None, flat])
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))), pa.int32()), values)
            equal = [not odd or odd.isdisjoint(words) for _, words in held]
            return pa.RecordBatch.from_arrays([pa.array([k for k, _ in held], pa.int64()), lists, pa.array(sizes), pa.array([len(w) for _, w in held], pa.int64()), pa.array(equal)], schema=schema)

        held, size = [], 0
        for batch in batches:
            for key, text in zip(*(c.to_pylist() for c in batch.columns)):
                words = split_words(text)
                held.append((key, words))
                size += len(text)
                if size >= HELD_CHARS:
                    yield hand_on(held)
                    held, size = [], 0
        if held:
            yield hand_on(held)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text")).mapInArrow(run, "doc_id long, ids array<int>, n_tokens long, n_words long, decoded_equal boolean")


class Decoder:
    def __init__(self, model: Model):
        low = model.bytes_at
        self.table = [bytes([i - low]) if low is not None and low <= i < low + 256 else p.replace(SPACE, " ").encode() for i, p in enumerate(model.by_id)]

    def raw(self, ids: list[int]) -> bytes:
        return b"".join(map(self.table.__getitem__, ids))

    def decode(self, ids: list[int]) -> str:
        out = self.raw(ids).decode("utf-8", "replace")
        return out[1:] if out[:1] == " " else out


def decode(tokens: DataFrame, model_path: str = MODEL, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(doc_id, text) from token ids; null ids give null."""
    shared = tokens.sparkSession.sparkContext.broadcast(load_model(model_path).values())

    def rows(source):
        decoder = Decoder(Model(*shared.value))
        for key, ids in source:
            yield key, None if ids is None else decoder.decode(ids)

    return map_rows(tokens, [F.col(id_col).cast("long"), F.col(ids_col)], "doc_id long, text string", rows)
