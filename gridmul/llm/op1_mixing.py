"""Mixing sources to target weights by soft membership.

A multinomial logistic classifier, trained on labelled rows, gives every document a posterior over domains (here the
classes of the `labels` table: good, poor, toxic). Document rates r >= 0 are fitted so that the expected tokens of each
domain, sum of rate * tokens * posterior, match the target totals: projected gradient steps on the squared errors of the
domains' shares, starting at rate 1, with a slight pull (PULL) towards 1. The pull settles which of the many exact fits is taken;
where a target is out of reach, as for a domain of which next to nothing is left, it keeps the rates of the other documents near 1
instead of following traces of that domain.

The gradient with regard to a document's rate is its posterior times the domains' errors, so all gradients so far are a vector
of one number a domain, and the projected rate is max(0, 1 - posterior . vector): nothing is kept or replayed by document. A step
is one aggregation over the rows; it gives the errors and the second moments of the rows that are not clipped, whose inverse
scales the next gradient, for several step lengths at once. The squared error with its pull is convex, each step lessens it, and
steps go on until the gradient vanishes: the result depends on no number of steps.

The training sample is bounded by TRAIN_ROWS labelled documents; posteriors, totals and rates cover all documents.

Defined cases: null text is empty text with 0 tokens, whose rate moves with its posterior like any other; very long texts are
read whole; labels without a document, or null, are left out; several rows of one labelled id train as one, the least text;
repeated rows are judged alike and so are ties, as a rate follows from the posterior alone; without usable labels the
posterior is 1 for the first domain; targets that no rates reach are met as nearly as the squared error allows; an empty table
gives an empty result; extra columns, whatever their names, are ignored.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridmul.llm.common import map_rows, materialise, sample_rows, text_of

DOMAINS = ("good", "poor", "toxic")
#: Share of all expected tokens that each domain shall have.
TARGETS = {"good": 0.98, "poor": 0.01, "toxic": 0.01}
TRAIN_ROWS = 4000
BUCKETS = 1 << 18
#: A word counts where the share of one domain's documents that hold it exceeds that of the others by so many standard errors.
MIN_EVIDENCE = 6.0
MIN_DOCUMENTS = 8
#: Gradient of each domain, as a share of the budget, at which the fit ends.
TOLERANCE = 1e-9
#: Weight of the pull towards rate 1 (mean over tokens) against the squared errors of shares. Where targets are easily reached, a
#: pull of x leaves errors of about x; a strong one keeps rates near 1 where they can be reached only by few telling documents.
PULL = 1e-7
#: Parts of a step that are tried at once.
LENGTHS = (1.0, 0.5, 0.2, 0.05, 0.005)
#: The default budget keeps the domain of the largest target whole, with this margin.
MARGIN = 1.02

#: The dense features, in order.
DENSE = "upper lower digit stop symbol bar distinct length bias".split()


class _Buckets(dict):
    def __missing__(self, word: str) -> int:
        if len(self) > 400_000:
            self.clear()
        self[word] = value = zlib.crc32(word.encode("utf-8", "surrogatepass")) % BUCKETS
        return value


def features(text: str, buckets: dict) -> tuple[int, np.ndarray, np.ndarray]:
    """(tokens, buckets of the distinct words, dense features)."""
    words = text.lower().split()
    unique = {w.strip(".,;:!?\"'()[]") for w in set(words)}
    at = np.unique(np.fromiter(map(buckets.__getitem__, unique), np.int64, len(unique)))
    codes = np.frombuffer(text.encode("latin-1", "replace"), np.uint8)
    n = max(len(codes), 1)
    kinds = np.bincount(codes, minlength=256) / n
    dense = np.array([
        kinds[65:91].sum() * 4,
        kinds[97:123].sum(),
        kinds[48:58].sum() * 4,
        kinds[[44, 46, 58, 59]].sum() * 4,
        kinds[[33, 35, 36, 37, 38, 42, 60, 62]].sum() * 8,
        kinds[124] * 8,
        len(unique) / max(len(words), 1),
        min(len(text) / max(len(words), 1) / 8, 4.0),
        1.0,
    ])
    return len(words), at, dense


def posterior(at: np.ndarray, dense: np.ndarray, model: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Softmax over the domains."""
    sparse, full = model
    z = full @ dense + sparse[:, at].sum(axis=1)
    p = np.exp(z - z.max())
    return p / p.sum()


def domain_of(quality: Column, toxic: Column) -> Column:
    return F.when(toxic == 1, "toxic").when(quality == 1, "good").when(quality == 0, "poor")


def _telling(cols: np.ndarray, owner: np.ndarray, y: np.ndarray, domains: int) -> np.ndarray:
    """Buckets that speak for a domain: enough documents, and a share in it well above the others'."""
    held = np.stack([np.bincount(cols[y[owner] == d], minlength=BUCKETS) for d in range(domains)]).astype(float)
    sizes, total = np.bincount(y, minlength=domains), held.sum(axis=0)
    out = np.zeros(BUCKETS, bool)
    share = total / len(y)
    for d in range(domains):
        other = len(y) - sizes[d]
        if sizes[d] and other:
            error = np.sqrt(np.maximum(share * (1 - share), 1e-12) * (1 / sizes[d] + 1 / other))
            out |= held[d] / sizes[d] - (total - held[d]) / other >= MIN_EVIDENCE * error
    return out & (total >= MIN_DOCUMENTS)


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", rows: int = TRAIN_ROWS, domains: tuple[str, ...] = DOMAINS) -> tuple[np.ndarray, np.ndarray]:
    """Weights (domain x bucket, domain x dense) from at most about `rows` labelled documents.

    labels: (doc_id, domain). The sample's ids are few by that bound, so they are broadcast and no text is shuffled."""
    some = sample_rows(labels.where(F.col("domain").isin(*domains)).select(F.col("doc_id"), "domain"), rows)
    found = docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text")).join(F.broadcast(some), "doc_id")
    # an id of several rows counts once, so that the sample keeps its bound
    sample = found.groupBy("doc_id").agg(F.min(F.struct("domain", "text")).alias("one")).select("one.domain", "one.text")

    def featured(source):
        buckets = _Buckets()
        for domain, text in source:
            _, at, dense = features(text, buckets)
            yield domain, at.tolist(), dense.tolist()

    got = map_rows(sample, [F.col("domain"), F.col("text")], "domain string, at array<int>, dense array<double>", featured).collect()
    sparse, full = np.zeros((len(domains), BUCKETS)), np.zeros((len(domains), len(DENSE)))
    if not got:
        full[0, -1] = 30.0
        return sparse, full
    got.sort(key=lambda r: (r.domain, r.at, r.dense))  # rows come in any order
    y = np.array([domains.index(r.domain) for r in got])
    cols, owner = np.concatenate([np.array(r.at, np.int64) for r in got]), np.repeat(np.arange(len(got)), [len(r.at) for r in got])
    telling = _telling(cols, owner, y, len(domains))[cols]
    owner = owner[telling]
    used, cols = np.unique(cols[telling], return_inverse=True)
    dense = np.array([r.dense for r in got])
    onehot = np.eye(len(domains))[y].T
    few = np.zeros((len(domains), len(used)))
    # diagonal (adaptive) gradient steps
    squares = [np.full_like(few, 1e-8), np.full_like(full, 1e-8)]
    for _ in range(150):
        z = full @ dense.T + np.stack([np.bincount(owner, few[d][cols], len(got)) for d in range(len(domains))])
        p = np.exp(z - z.max(axis=0))
        err = (p / p.sum(axis=0) - onehot) / len(got)
        grads = [np.stack([np.bincount(cols, err[d][owner], len(used)) for d in range(len(domains))]) + 1e-4 * few, err @ dense + 1e-6 * full]
        for w, g, q in zip((few, full), grads, squares):
            q += g * g
            w -= 0.2 * g / np.sqrt(q)
    sparse[:, used] = few
    return sparse, full


def memberships(docs: DataFrame, model: tuple[np.ndarray, np.ndarray], id_col: str = "doc_id", text_col: str = "text", keep: list[Column] | None = None) -> DataFrame:
    """(doc_id, n_tokens, p): a posterior for every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # of a fixed size: domains x (buckets + dense)

    def rows(source):
        buckets = _Buckets()
        for key, text in source:
            n, at, dense = features(text, buckets)
            yield key, n, posterior(at, dense, shared.value).tolist()

    return map_rows(docs, [F.col(id_col).cast("long"), text_of(text_col)], "doc_id long, n_tokens long, p array<double>", rows)


@dataclass(frozen=True)
class Fit:
    """push: all scaled gradients so far, a number a domain; share, error: of the expected tokens, by domain; steps taken."""

    push: np.ndarray
    share: np.ndarray
    error: np.ndarray
    steps: int


def rates_of(p: np.ndarray, push: np.ndarray) -> np.ndarray:
    """Rates of documents with posteriors p: moved along all gradients, projected to what is not negative."""
    return np.maximum(0.0, 1.0 - p @ push)


def _arrays(batch: pa.RecordBatch, d: int) -> tuple[np.ndarray, np.ndarray]:
    """Token counts and posteriors of a batch (n_tokens, p)."""
    return batch.column(0).to_numpy(zero_copy_only=False).astype(float), batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, d)


def _sums(members: DataFrame, pushes: list[np.ndarray], d: int) -> list[tuple[np.ndarray, np.ndarray, float]]:
    """For each push: expected tokens by domain, second moments of the rows above rate 0, sum of tokens * rate^2. One pass."""
    size = d + d * d + 1

    def run(batches):
        total = np.zeros((len(pushes), size))
        for batch in batches:
            t, p = _arrays(batch, d)
            for k, push in enumerate(pushes):
                r = rates_of(p, push)
                above = p * (t * (r > 0))[:, None]
                total[k] += np.concatenate(((t * r) @ p, (above.T @ p).ravel(), [(t * r * r).sum()]))
        yield pa.RecordBatch.from_pydict({"i": pa.array(range(total.size), pa.int32()), "x": total.ravel()})

    out = np.zeros(len(pushes) * size)
    for r in members.select("n_tokens", "p").mapInArrow(run, "i int, x double").groupBy("i").agg(F.sum("x").alias("x")).collect():
        out[r.i] = r.x
    return [(x[:d], x[d:-1].reshape(d, d), x[-1]) for x in out.reshape(len(pushes), size)]


def fit_rates(members: DataFrame, targets: list[float], budget: float | None = None, tolerance: float = TOLERANCE, pull: float = PULL) -> Fit:
    """The fit to `targets` (shares that sum to 1) of the members (n_tokens, p)."""
    d = len(targets)
    want = np.array(targets, float) / sum(targets)
    push = np.zeros(d)
    [(x, second, square)] = _sums(members, [push], d)
    if not x.sum():
        return Fit(push, np.zeros(d), np.zeros(d), 0)
    main = int(want.argmax())
    total = budget or MARGIN * x[main] / want[main]
    steps = 0
    while True:
        # all as shares of the budget
        gradient = x / total - want - pull * push
        value = square / total / 2 + want @ push + pull * (push @ push) / 2
        if np.abs(gradient).max() <= tolerance:
            break
        move = np.linalg.solve(second / total + pull * np.eye(d), gradient)
        tried = [push + k * move for k in LENGTHS]
        found = _sums(members, tried, d)
        values = [s / total / 2 + want @ at + pull * (at @ at) / 2 for at, (_, _, s) in zip(tried, found)]
        k = int(np.argmin(values))
        if values[k] >= value:  # no step length lessens it: the numbers have no more digits
            break
        push, (x, second, square), steps = tried[k], found[k], steps + 1
    return Fit(push, x / total, x / total - want, steps)


def rates(members: DataFrame, fit: Fit) -> DataFrame:
    """members with the rate of each row."""
    d = len(fit.push)

    def run(batches):
        for batch in batches:
            _, p = _arrays(batch.select(["n_tokens", "p"]), d)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(rates_of(p, fit.push))], names=["doc_id", "n_tokens", "p", "rate"])

    return members.select("doc_id", "n_tokens", "p").mapInArrow(run, "doc_id long, n_tokens long, p array<double>, rate double")


def mix(docs: DataFrame, labels: DataFrame, targets: dict[str, float] = TARGETS, id_col: str = "doc_id", text_col: str = "text", budget: float | None = None, pull: float = PULL) -> DataFrame:
    """(doc_id, n_tokens, p, rate, share_error) for every row of docs; labels: (doc_id, domain). share_error, the same in all rows:
    the largest difference between a domain's share of the budget and its target."""
    names = tuple(targets)
    members = materialise(memberships(docs, train(docs, labels, id_col, text_col, domains=names), id_col, text_col), "members")
    fit = fit_rates(members, [targets[n] for n in names], budget, pull=pull)
    return rates(members, fit).withColumn("share_error", F.lit(float(np.abs(fit.error).max())))


def label_domains(labels: DataFrame) -> DataFrame:
    """(doc_id, domain) of the `labels` table; a document with several labels counts once, with the worst."""
    return labels.select("doc_id", domain_of(F.col("quality"), F.col("toxic")).alias("domain")).where("doc_id IS NOT NULL AND domain IS NOT NULL").groupBy("doc_id").agg(F.max("domain").alias("domain"))


def copies(rate: Column, *keys: Column) -> Column:
    """How often a row is taken: the rate, rounded up or down by a fixed hash of its keys."""
    return F.floor(rate + F.pmod(F.xxhash64(*keys), F.lit(1 << 20)) / F.lit(float(1 << 20))).cast("int")
