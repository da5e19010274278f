"""Quality rules by distribution divergence.

Every text gets a histogram of character classes and one of common words. What is common is learnt: words fall into WORD_BUCKETS
hash buckets, and the COMMON heaviest buckets of a language, over all texts that pass the base rules, are its common words.
References are the mean histograms of each language over the same texts; a text is kept when the Jensen-Shannon distances
(base 2, 0 to 1) to the reference of its language stay below two thresholds. Short texts have noisy histograms, so each
comparison has a minimum length under which it does not speak. Simple counts (length, repeated three-word windows) come first.

Defined cases: null text is empty text and fails the base rule; very long texts are read whole; a null language is compared with
every reference and the nearest one counts, the first of the alphabet on a tie; a language with fewer than MIN_DOCUMENTS texts (or
MIN_SHARE of all) that pass the base rules has no reference, and its texts are judged by the base rules alone; buckets of one weight are taken by number;
repeated rows are judged alike; an empty table gives an empty result and needs no reference; extra columns, whatever their names,
are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from gridmul.llm.common import map_rows, materialise, text_of

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SYMBOLS = "#*$%&|<>"

#: Hash buckets of words, and how many of the heaviest are a language's common words.
WORD_BUCKETS = 1 << 14
COMMON = 24
#: Texts that a language's reference takes at least, and the share of all texts, which bounds the number of references.
MIN_DOCUMENTS = 20
MIN_SHARE = 1e-4

#: Names of the character classes, in histogram order.
CLASSES = "lower upper accented_lower accented_upper other_letter digit blank newline stop bracket symbol other".split()

MIN_WORDS = 50
#: Words (characters) under which the word (class) comparison does not speak.
MIN_WORDS_COMPARED = 80
MIN_CHARS_COMPARED = 200
MAX_CLASS_DISTANCE = 0.26
#: The word distance of a sound text falls with its length as its sampling noise does: the bound is MAX + NOISE / sqrt(words).
MAX_WORD_DISTANCE = 0.225
WORD_NOISE = 1.3


def _class_table() -> np.ndarray:
    kinds = np.empty(0x250, np.uint8)
    for code in range(0x250):
        c = chr(code)
        if c.isascii() and c.islower():
            name = "lower"
        elif c.isascii() and c.isupper():
            name = "upper"
        elif c.islower():
            name = "accented_lower"
        elif c.isupper():
            name = "accented_upper"
        elif c.isalpha():
            name = "other_letter"
        elif c.isdigit():
            name = "digit"
        elif c in "\n\r\v\f":
            name = "newline"
        elif c.isspace():
            name = "blank"
        elif c in ".,;:!?'\"-":
            name = "stop"
        elif c in "()[]{}":
            name = "bracket"
        elif c in "#*$%&|<>+=@^_~/\\`":
            name = "symbol"
        else:
            name = "other"
        kinds[code] = CLASSES.index(name)
    return kinds


_KINDS = _class_table()


def class_histogram(text: str) -> np.ndarray:
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    low = codes[codes < len(_KINDS)]
    counts = np.bincount(_KINDS[low], minlength=len(CLASSES))
    counts[CLASSES.index("other_letter")] += len(codes) - len(low)
    return counts


class _Buckets(dict):
    """Word to bucket, whatever its case and closing punctuation; forgets all when large."""

    def __missing__(self, word: str) -> int:
        if len(self) > 400_000:
            self.clear()
        self[word] = value = zlib.crc32(word.lower().rstrip(".,;:!?").encode("utf-8", "surrogatepass")) % WORD_BUCKETS
        return value


def word_histogram(counts: Counter, common: list[int], buckets: dict) -> np.ndarray:
    """Words in each common bucket, last in all others."""
    place = {w: i for i, w in enumerate(common)}
    out = np.zeros(len(common) + 1, np.int64)
    last = len(common)
    for word, n in counts.items():
        out[place.get(buckets[word], last)] += n
    return out


def repeated_words(words: list[str]) -> int:
    """Words inside three-word windows that occur twice or more, the first occurrence included."""
    n = len(words)
    if n < 4:
        return 0
    ids: dict[str, int] = {}
    w = np.fromiter((ids.setdefault(x, len(ids)) for x in words), np.int64, n)
    size = len(ids)
    if size < 2_000_000:
        keys = (w[:-2] * size + w[1:-1]) * size + w[2:]
    else:  # the product would not fit 64 bits
        keys = np.unique(np.stack((w[:-2], w[1:-1], w[2:]), 1), axis=0, return_inverse=True)[1].ravel()
    order = np.argsort(keys, kind="stable")
    s = keys[order]
    same = s[1:] == s[:-1]
    hit = np.zeros(n - 2, bool)
    hit[order[1:][same]] = True
    hit[order[:-1][same]] = True
    cover = np.zeros(n, bool)
    cover[:-2] |= hit
    cover[1:-1] |= hit
    cover[2:] |= hit
    return int(cover.sum())


def base_counts(text: str, words: list[str]) -> tuple[int, int, int, int, int]:
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words)."""
    seen: set[str] = set()
    dup = 0
    for line in text.split("\n"):
        if line in seen:
            dup += WORD.search(line) is not None
        else:
            seen.add(line)
    return len(words), sum(map(len, words)), sum(map(text.count, SYMBOLS)), dup, repeated_words(words)


def fails(n_words: int, n_repeat_words: int) -> bool:
    return n_words < MIN_WORDS or 100 * n_repeat_words > 50 * n_words


def distance(p: np.ndarray, q: np.ndarray) -> float:
    """Jensen-Shannon distance in base 2; 0 when either has no mass."""
    if not p.sum() or not q.sum():
        return 0.0
    p, q = p / p.sum(), q / q.sum()
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        d = np.where(p > 0, p * np.log2(p / m), 0).sum() / 2 + np.where(q > 0, q * np.log2(q / m), 0).sum() / 2
    return float(np.sqrt(max(d, 0.0)))


PROFILE = "doc_id long, lang string, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, classes array<long>, words map<string,array<long>>"


def _columns(docs: DataFrame, id_col: str, text_col: str, lang_col: str) -> list:
    return [F.col(id_col).cast("long"), text_of(text_col), F.col(lang_col).cast("string") if lang_col in docs.columns else F.lit(None).cast("string")]


def common_words(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", common: int = COMMON) -> dict[str, list[int]]:
    """The heaviest buckets of each language over all texts that pass the base rules: `common` numbers a language.

    A task sends at most a row for each of its languages and buckets, whatever it reads."""
    if lang_col not in docs.columns:
        return {}

    def rows(source):
        sums: dict[str, np.ndarray] = {}
        held, buckets = Counter(), _Buckets()
        for text, lang in source:
            words = WORD.findall(text)
            if lang is not None and not fails(len(words), repeated_words(words)):
                held[lang] += 1
                at = sums.setdefault(lang, np.zeros(WORD_BUCKETS, np.int64))
                at += np.bincount(np.fromiter(map(buckets.__getitem__, words), np.int64, len(words)), minlength=WORD_BUCKETS)
        for lang, at in sums.items():
            yield lang, -1, held[lang]
            for bucket in np.flatnonzero(at).tolist():
                yield lang, bucket, int(at[bucket])

    sums = map_rows(docs, [text_of(text_col), F.col(lang_col).cast("string")], "lang string, bucket int, n long", rows).groupBy("lang", "bucket").agg(F.sum("n").alias("n"))
    sums = materialise(sums, "common-words", narrow=True)
    texts = sums.where("bucket < 0")
    least = max(MIN_DOCUMENTS, MIN_SHARE * (texts.agg(F.sum("n")).first()[0] or 0))
    place = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "bucket"))
    ranked = sums.where("bucket >= 0").join(texts.where(F.col("n") >= least).select("lang"), "lang", "left_semi").withColumn("place", place)
    out: dict[str, list[int]] = {}
    for r in ranked.where(F.col("place") <= common).orderBy("lang", "place").collect():  # at most `common` / MIN_SHARE rows
        out.setdefault(r.lang, []).append(r.bucket)
    return out


def profiles(docs: DataFrame, common: dict[str, list[int]], id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """The counts and histograms of every text: the word histogram of its language, of all languages where it is null."""

    def rows(source):
        buckets = _Buckets()
        for key, text, lang in source:
            words = WORD.findall(text)
            counts = Counter(words)
            wanted = common if lang is None else {lang: common[lang]} if lang in common else {}
            hists = {x: word_histogram(counts, at, buckets).tolist() for x, at in wanted.items()}
            yield key, lang, *base_counts(text, words), class_histogram(text).tolist(), hists

    return map_rows(docs, _columns(docs, id_col, text_col, lang_col), PROFILE, rows)


def references(profiled: DataFrame) -> dict[str, tuple[list[int], list[int]]]:
    """Mean histograms (in millionths) of each language over all texts that pass the base rules.

    The sums hold a row for each language and bin, at most a few hundred, whatever the input."""

    def rows(source):
        sums: Counter = Counter()
        for lang, n, repeat, classes, words in source:
            words = dict(words)
            if lang in words and not fails(n, repeat):
                for kind, hist in (("c", classes), ("w", words[lang])):
                    total = sum(hist)
                    for i, x in enumerate(hist):
                        sums[lang, kind, i] += round(1_000_000 * x / total) if total else 0
        for (lang, kind, i), x in sums.items():
            yield lang, kind, i, x

    part = map_rows(profiled, [F.col(c) for c in ("lang", "n_words", "n_repeat_words", "classes", "words")], "lang string, kind string, bin int, x long", rows)
    sums = {(r.lang, r.kind, r.bin): r.x for r in part.groupBy("lang", "kind", "bin").agg(F.sum("x").alias("x")).collect()}
    langs = sorted({x for x, _, _ in sums})
    return {x: tuple([sums[x, kind, i] for i in range(sum(k[:2] == (x, kind) for k in sums))] for kind in "cw") for x in langs}


def judge(profiled: DataFrame, refs: dict[str, tuple[list[int], list[int]]], max_class: float = MAX_CLASS_DISTANCE, max_word: float = MAX_WORD_DISTANCE) -> DataFrame:
    """(doc_id, the counts, base_failed, class_distance, word_distance, kept)."""
    arrays = {lang: (np.array(c, float), np.array(w, float)) for lang, (c, w) in sorted(refs.items())}

    def rows(source):
        for key, lang, n, chars, symbols, dup, repeat, classes, words in source:
            words = dict(words)
            failed = fails(n, repeat)
            pick = [x for x in arrays if x in words]
            c = np.array(classes, float)
            long_enough = (c.sum() >= MIN_CHARS_COMPARED, n >= MIN_WORDS_COMPARED)
            both = [(distance(c, arrays[x][0]) if long_enough[0] else 0.0, distance(np.array(words[x], float), arrays[x][1]) if long_enough[1] else 0.0) for x in pick]
            dc, dw = min(both, key=sum) if both else (0.0, 0.0)
            yield key, n, chars, symbols, dup, repeat, failed, dc, dw, not failed and dc <= max_class and (n < MIN_WORDS_COMPARED or dw <= max_word + WORD_NOISE / n**0.5)

    schema = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, class_distance double, word_distance double, kept boolean"
    return map_rows(profiled, [F.col(c) for c in profiled.columns], schema, rows)


def quality(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Common words of all texts, profiles with them (written to the shared folder), references, then a verdict per document."""
    profiled = materialise(profiles(docs, common_words(docs, text_col, lang_col), id_col, text_col, lang_col), "profiles")
    return judge(profiled, references(profiled))
