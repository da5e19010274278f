"""Personal data by rules and by bootstrapped contextual extraction, in DataFrame functions only.

Rules find emails, IP addresses, card and phone numbers. These spans, and long random-looking tokens (which no rule reports),
are the seeds of a graph of patterns and instances. Instances are the tokens that look like identifiers: with a digit, `@` or `_`,
quoted, or after `=` or `:`, with or without digits. Patterns are what stands around them: the word before, the two words before,
the words on both sides, and the key of an assignment (`key = value`, blanks or not), all lower-cased and without marks at their
ends. A pattern's score is the mean score of its distinct instances; one with enough score and support is accepted and hands its
score to its instances, which then count as seeds of other patterns, until nothing changes any more. Every token in an accepted
pattern is a find, reported as a span of kind `context`.

Positions come from splitting: the pieces between the matches and the matches themselves alternate, so their lengths add
up to code-point offsets. Possessive quantifiers and a look-behind keep each expression linear and free of recursion on
very long runs; neither changes what it matches.

Defined cases: null text is empty text without spans; very long texts, words and keys are read whole; repeated rows give repeated
results; one instance that occurs many times counts once for a pattern; base spans of different kinds may overlap and all stay, in
the order of start and then kind; a token that overlaps a base span is no find of its own; an empty table gives an empty result;
extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridmul.llm.common import materialise, text_of

#: The kinds in the order that breaks ties, with the expression of each.
KINDS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:(?<![0-9])|\G)[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: What a text must hold for the expression to be worth running.
NEEDS = {"email": "@", "ip": ".", "card": None, "phone": "+"}

#: A whole token that looks like an identifier.
CANDIDATE = r"(?<!\S)(?:(?=[^\s0-9@_=:]*+(?:[0-9@_]|[=:][\x22\x27]?\w))|(?=[\x22\x27(<\[{]++\w)|(?<=[=:][\x20\t]{1,4}))\S++"
#: What a text must hold for the expression to be worth running.
MARKS = r"[0-9@_=:\x22\x27(<\[{]"
#: A random-looking token: so long, letters and digits mixed in so many places.
RANDOM = r"^(?=(?:[^0-9]*+[0-9]){4})(?=(?:[^A-Za-z]*+[A-Za-z]){4})(?=(?:[0-9]*+[A-Za-z]++[0-9]){3})[A-Za-z0-9+/_=-]{24,}+$"

#: Score of a random-looking seed; a base span's is 1.
RANDOM_SCORE = 0.8
#: Distinct instances of at least MIN_CONFIDENCE that an accepted pattern has.
MIN_SUPPORT = 3
MIN_CONFIDENCE = 0.6
SMOOTHING = 1.0
#: Change of a score that counts as one.
TOLERANCE = 0.001
#: Parts that the instances of a pattern are dealt to in joins, as a common word is a hot key.
SALTS = 8


def _sql(text: str) -> str:
    return f"r'{text}'"  # the expressions hold no quotes


_MATCHES = "array<struct<start:int,hit:string>>"


def with_matches(df: DataFrame, patterns: dict[str, tuple[str, Column]]) -> DataFrame:
    """Add a column for each (name: expression, condition under which `text` can match it): all leftmost
    non-overlapping matches as (start, hit), start in code points from 0; hits_<name> and pieces_<name> stay."""
    # hits and pieces are columns of their own, so that each expression runs once for a row
    cut = df.select("*", *[F.when(c, F.expr(f"regexp_extract_all(text, {_sql(p)}, 0)")).alias(f"hits_{n}") for n, (p, c) in patterns.items()], *[F.when(c, F.expr(f"split(text, {_sql(p)}, -1)")).alias(f"pieces_{n}") for n, (p, c) in patterns.items()])

    def placed(n: str) -> Column:
        return F.expr(f"""
            aggregate(
              zip_with(hits_{n}, slice(pieces_{n}, 1, size(hits_{n})), (h, b) -> named_struct('hit', h, 'before', b)),
              named_struct('at', 0, 'out', CAST(array() AS {_MATCHES})),
              (acc, m) -> named_struct(
                'at', acc.at + length(m.before) + length(m.hit),
                'out', concat(acc.out, array(named_struct('start', acc.at + length(m.before), 'hit', m.hit)))),
              acc -> acc.out)""")

    return cut.select("*", *[F.coalesce(placed(n), F.expr(f"CAST(array() AS {_MATCHES})")).alias(n) for n in patterns])


#: Conditions on a match m of each kind.
_DIGITS = "regexp_replace(m.hit, '[^0-9]', '')"
_VALID = {
    "email": "true",
    "ip": r"forall(split(m.hit, r'\.'), p -> length(ltrim('0', p)) <= 3 AND CAST(coalesce(nullif(right(ltrim('0', p), 3), ''), '0') AS INT) <= 255)",
    "card": f"""length({_DIGITS}) BETWEEN 14 AND 19 AND aggregate(sequence(1, least(greatest(length({_DIGITS}), 1), 19)), 0, (a, i) -> a
        + CASE WHEN i % 2 = 1 THEN CAST(substring({_DIGITS}, -i, 1) AS INT)
               ELSE CAST(substring({_DIGITS}, -i, 1) AS INT) * 2 - IF(CAST(substring({_DIGITS}, -i, 1) AS INT) > 4, 9, 0) END) % 10 = 0""",
    "phone": f"length({_DIGITS}) BETWEEN 10 AND 15",
}
_SPANS = "array<struct<start:int,rank:int,end:int>>"


def _spans(column: str, kind: str, rank: int) -> Column:
    return F.expr(f"transform(filter({column}, m -> {_VALID[kind]}), m -> named_struct('start', m.start, 'rank', {rank}, 'end', m.start + length(m.hit)))")


def base_and_candidates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, uid, n_<kind>..., base, candidates), written to the shared folder; the texts stay behind."""
    t = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text"))
    t = t.withColumn("has_digit", F.col("text").rlike("[0-9]"))
    digit = F.col("has_digit")
    found = {k: (p, digit if k == "card" else F.contains(F.col("text"), F.lit(NEEDS[k])) & (digit | F.lit(k == "email"))) for k, p in KINDS.items()}
    t = with_matches(t, {f"m_{k}": v for k, v in found.items()} | {"tokens": (CANDIDATE, F.col("text").rlike(MARKS))})
    t = t.select("doc_id", "text", *[_spans(f"m_{k}", k, i).alias(k) for i, k in enumerate(KINDS)], "tokens", "pieces_tokens")
    base = F.array_sort(F.concat(*KINDS))
    # tokens alternate with the pieces between them: the two words before one lie in the piece before it, else in the token before
    # that, and so on; the word after it in the next piece or token
    edge = r"^[^\\p{L}\\p{N}]+|[^\\p{L}\\p{N}]+$"
    opening = r"^[\\x22\\x27(<\\[{]*+"
    key = r"[\\p{L}_][\\p{L}\\p{N}_.-]*+(?=[=:])"
    around = F.expr(rf"""
        transform(tokens, (m, i) -> named_struct(
          'start', m.start, 'hit', m.hit,
          'skip', length(regexp_extract(m.hit, '{opening}(?:{key}[=:](?=.))?[\\x22\\x27]*+', 0)),
          'key', regexp_extract(m.hit, '{opening}({key})[=:](?=.)', 1),
          'near', filter(split(lower(concat(IF(i > 1, tokens[i - 2].hit, ''), IF(i > 0, concat(pieces_tokens[i - 1], tokens[i - 1].hit), ''), pieces_tokens[i])), r'\s+'), w -> w <> ''),
          'right', lower(regexp_extract(concat(pieces_tokens[i + 1], coalesce(get(tokens, i + 1).hit, '')), r'^\s*+(\S++)', 1))))""")
    t = t.select("doc_id", "text", F.monotonically_increasing_id().alias("uid"), *[F.size(k).cast("long").alias(f"n_{k}") for k in KINDS], base.alias("base"), "tokens", around.alias("c"))
    words = F.expr(rf"""
        transform(filter(c, c -> length(c.hit) > c.skip), c -> named_struct(
          'start', c.start + c.skip,
          'instance', regexp_replace(substring(c.hit, c.skip + 1), r'[^\p{{L}}\p{{N}}=+/_-]+$', ''),
          'key', regexp_replace(CASE
            WHEN c.key <> '' THEN lower(c.key)
            WHEN size(c.near) > 1 AND try_element_at(c.near, -1) rlike r'^[=:]+$' THEN try_element_at(c.near, -2)
            WHEN size(c.near) > 0 AND try_element_at(c.near, -1) rlike r'[=:]$' THEN try_element_at(c.near, -1) ELSE '' END, '{edge}', ''),
          'left', regexp_replace(IF(size(c.near) > 0, try_element_at(c.near, -1), ''), '{edge}', ''),
          'far', regexp_replace(IF(size(c.near) > 1, try_element_at(c.near, -2), ''), '{edge}', ''),
          'right', regexp_replace(c.right, '{edge}', '')))""")
    t = t.withColumn("c", words)
    # a base span is one instance, whole, in the place of the first token that it meets
    t = t.withColumn("c", F.expr(r"transform(filter(c, x -> x.instance rlike r'[\p{L}\p{N}]'), x -> named_struct('x', x, 'base', filter(base, b -> b.start < x.start + length(x.instance) AND x.start < b.end)))"))
    candidates = F.expr(rf"""
        transform(filter(c, c -> NOT exists(c.base, b -> b.start < c.x.start AND exists(tokens, m -> m.start < c.x.start AND m.start + length(m.hit) > b.start))), c -> named_struct(
          'start', c.x.start, 'end', c.x.start + length(c.x.instance),
          'instance', IF(size(c.base) = 0, c.x.instance, substring(text, c.base[0].start + 1, c.base[0].end - c.base[0].start)),
          'patterns', array_compact(array(
            IF(c.x.key = '', NULL, concat('key ', c.x.key)),
            IF(c.x.left = '', NULL, concat('before ', c.x.left)),
            IF(c.x.left = '' OR c.x.far = '', NULL, concat('before ', c.x.far, ' ', c.x.left)),
            IF(c.x.left = '' OR c.x.right = '', NULL, concat('between ', c.x.left, ' ', c.x.right)))),
          'base', size(c.base) > 0,
          'random', c.x.instance rlike {_sql(RANDOM)}))""")
    return materialise(t.withColumn("candidates", F.coalesce(candidates, F.expr("CAST(array() AS array<struct<start:int,`end`:int,instance:string,patterns:array<string>,base:boolean,random:boolean>>)"))).drop("c", "text", "tokens"), "pii")


def pattern_edges(found: DataFrame) -> DataFrame:
    """(pattern, instance, seed): every distinct pair once, with the instance's score of its own."""
    rows = found.select(F.explode("candidates").alias("c")).select(F.explode("c.patterns").alias("pattern"), F.col("c.instance").alias("instance"), F.when(F.col("c.base"), 1.0).when(F.col("c.random"), RANDOM_SCORE).otherwise(0.0).alias("seed"))
    return materialise(rows.groupBy("pattern", "instance").agg(F.max("seed").alias("seed")), "pii-edges", narrow=True)


def _dealt(rows: DataFrame) -> DataFrame:
    return rows.withColumn("salt", F.pmod(F.xxhash64("instance"), F.lit(SALTS)).cast("int"))


def _everywhere(patterns: DataFrame) -> DataFrame:
    return patterns.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))


def score_patterns(edges: DataFrame, min_support: int = MIN_SUPPORT, min_confidence: float = MIN_CONFIDENCE) -> DataFrame:
    """(pattern, score, support, accepted): the graph scored in turns, until no score changes.

    Scores only grow from round to round, as accepted patterns raise their instances, so the rounds end."""

    def of_patterns(scored: DataFrame) -> DataFrame:
        score = F.sum("score") / (F.count("*") + SMOOTHING)
        support = F.count(F.when(F.col("score") >= min_confidence, 1))
        both = scored.groupBy("pattern").agg(score.alias("score"), support.alias("support"))
        return materialise(both.withColumn("accepted", (F.col("score") >= min_confidence) & (F.col("support") >= min_support)), "pii-patterns", narrow=True)

    patterns = of_patterns(edges.withColumnRenamed("seed", "score"))
    while True:
        given = _dealt(edges).join(_everywhere(patterns.where("accepted").select("pattern", "score")), ["pattern", "salt"]).groupBy("instance").agg(F.max("score").alias("given"))
        scored = edges.join(given, "instance", "left").select("pattern", F.greatest("seed", F.coalesce("given", F.lit(0.0))).alias("score"))
        before, patterns = patterns, of_patterns(scored)
        grown = patterns.join(before.select("pattern", F.col("score").alias("s"), F.col("accepted").alias("a")), "pattern")
        if grown.where((F.col("score") > F.col("s") + TOLERANCE) | (F.col("accepted") != F.col("a"))).isEmpty():
            return patterns


def personal_data(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_support: int = MIN_SUPPORT, min_confidence: float = MIN_CONFIDENCE) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, n_context, base, context): spans as arrays of (start, rank, end)."""
    found = base_and_candidates(docs, id_col, text_col)
    sure = score_patterns(pattern_edges(found), min_support, min_confidence).where("accepted").select("pattern")
    unseen = found.select("uid", F.explode("candidates").alias("c")).where("NOT c.base").select("uid", "c.start", "c.end", "c.instance", F.explode("c.patterns").alias("pattern"))
    context = _dealt(unseen).join(_everywhere(sure), ["pattern", "salt"], "left_semi").groupBy("uid").agg(F.array_sort(F.collect_set(F.struct("start", F.lit(len(KINDS)).alias("rank"), "end"))).alias("context"))
    joined = found.drop("candidates").join(context, "uid", "left").withColumn("context", F.coalesce("context", F.expr(f"CAST(array() AS {_SPANS})")))
    return joined.select("doc_id", *[f"n_{k}" for k in KINDS], F.size("context").cast("long").alias("n_context"), "base", "context")


def span_text(spans: Column) -> Column:
    """kind:start:end, comma-joined, by start and then kind."""
    kinds = F.array(*[F.lit(k) for k in (*KINDS, "context")])
    return F.array_join(F.transform(F.array_sort(spans), lambda s: F.concat_ws(":", F.element_at(kinds, s["rank"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")
