"""Mixing sources to target weights by soft membership.

A softmax classifier, fitted on the labelled table, gives every document a posterior over domains.  Nonnegative rates
are then fitted so that the expected tokens of each domain, sum of rate * tokens * posterior, match target totals.  The
weighted least-squares problem is solved by projected gradient steps: each step needs one small aggregate of the corpus
and one residual vector of the driver; a document's rate is a fixed function of its posterior and the residuals sent so
far, so no rate ever has to be stored or joined.

Rates are clipped to [floor, cap].  Realised copies are the rate's whole part plus one with the probability of the
rest, drawn from a hash of id and text.  Domains are all values of the label in the labelled rows; null labels are
left out.  Null text counts as empty with zero tokens and the classifier's prior posterior; repeated rows are drawn alike; without
labelled rows there is one domain and every rate is the target total over the corpus; an empty table gives no rows;
extra columns pass through `mix`.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paircuration.llm.common import pieces, settle

BUCKETS = 512
PER_DOMAIN = 1500  # labelled rows of a domain that the classifier is expected to see, and
MOST_ROWS = 12_000  # of all domains together (but eight of a domain at least)


def features(text: bytes) -> tuple[np.ndarray, int]:
    """Square-rooted frequencies of hashed byte pairs of the lower-cased text, and its words."""
    data = np.frombuffer(text.lower(), dtype=np.uint8).astype(np.int64)
    pair = (data[:-1] * 31 + data[1:] * 257 + (data[:-1] >> 3)) % BUCKETS
    counts = np.bincount(pair, minlength=BUCKETS)
    return np.sqrt(counts / max(1, len(pair))), len(text.split())


class Membership:
    """Softmax weights over hashed byte pairs."""

    def __init__(self, domains: list[str], weights: np.ndarray):
        self.domains, self.weights = domains, weights

    def posteriors(self, x: np.ndarray) -> np.ndarray:
        z = x @ self.weights[:-1] + self.weights[-1]
        z = np.exp(z - z.max(axis=1, keepdims=True))
        return z / z.sum(axis=1, keepdims=True)


def fit_membership(docs: DataFrame, labelled: DataFrame, domain_col: str, id_col: str = "doc_id", text_col: str = "text",
                   per_domain: int = PER_DOMAIN, most_rows: int = MOST_ROWS, rounds: int = 300) -> Membership:
    """Fit on a sample of about `per_domain` labelled documents of each domain, and about `most_rows` in all.

    `labelled` has the id and the domain of the rows whose domain is known.  A row is in the sample if the hash of its id
    is below its domain's share, so small domains are there whole and no domain is left out.
    """
    marked = labelled.select(F.col(id_col).alias("row_key"), F.col(domain_col).cast("string").alias("domain")).na.drop()
    held = marked.groupBy("domain").agg(F.count(F.lit(1)).alias("n"))
    domains = sorted(r[0] for r in held.collect())
    if not domains:
        return Membership(["all"], np.zeros((BUCKETS + 1, 1)))
    each = max(8, min(per_domain, most_rows // len(domains)))
    draw = F.pmod(F.xxhash64("row_key", F.lit("mixing")), F.lit(1 << 30)) / float(1 << 30)
    chosen = marked.join(held, "domain").filter(draw < F.lit(float(each)) / F.col("n")).select("domain", "row_key")

    def measure(batches):
        for batch in batches:
            texts = pc.fill_null(batch.column(1), "").cast(pa.large_binary())
            yield pa.record_batch([batch.column(0), pa.array([features(t.as_py())[0].astype(np.float32).tobytes() for t in texts], pa.binary())], names=["domain", "x"])

    rows = docs.select(F.col(id_col).alias("row_key"), F.col(text_col).cast("string").alias("body")).join(
        F.broadcast(chosen), "row_key").select("domain", "body").mapInArrow(measure, "domain string, x binary").toPandas()
    x = np.stack([np.frombuffer(b, np.float32) for b in rows["x"]]).astype(np.float64) if len(rows) else np.zeros((0, BUCKETS))
    y = np.array([domains.index(d) for d in rows["domain"]], dtype=np.int64)
    x = np.hstack([x, np.ones((len(x), 1))])
    order = np.lexsort((x[:, 0], x.sum(axis=1), y))  # the same sums whatever order the rows came in
    x, y = x[order], y[order]
    target = np.eye(len(domains))[y]
    weights, speed = np.zeros((BUCKETS + 1, len(domains))), np.zeros((BUCKETS + 1, len(domains)))
    rate = 4.0
    for _ in range(rounds):  # heavy-ball descent on the ridge log loss
        z = x @ weights
        z = np.exp(z - z.max(axis=1, keepdims=True)) if len(z) else z
        p = z / z.sum(axis=1, keepdims=True) if len(z) else z
        grad = x.T @ (p - target) / max(1, len(x)) + 1e-5 * weights
        speed = 0.9 * speed - rate * grad
        weights = weights + speed
    return Membership(domains, weights)


def replay(p: np.ndarray, steps: np.ndarray, floor: float, cap: float) -> np.ndarray:
    """Rates after the steps sent so far: each moves a rate by posterior . step and projects it onto [floor, cap]."""
    rate = np.full(len(p), min(max(1.0, floor), cap))
    for s in steps:
        rate = np.clip(rate + p @ s, floor, cap)
    return rate


def fit_rates(members: DataFrame, targets: np.ndarray, floor: float, cap: float, rounds: int = 60, tolerance: float = 1e-3) -> tuple[np.ndarray, list[float]]:
    """Projected-gradient steps for min sum_k (T_k - sum_i rate_i n_i p_ik)^2 / m_k over floor <= rate <= cap.

    Gradients are scaled per document by its tokens, and m_k is the domain's own mass, which makes a unit step safe.
    `members` has tokens and the posterior array; returns the steps and the relative error after each.
    """
    k = len(targets)
    steps, errors, mass = np.zeros((0, k)), [], None
    for _ in range(rounds):
        sent = members.sparkSession.sparkContext.broadcast(steps)

        def sums(batches, sent=sent):
            total = np.zeros(k)
            for batch in batches:
                p = np.stack(batch.column(1).to_numpy(zero_copy_only=False)) if len(batch) else np.zeros((0, k))
                total += (replay(p, sent.value, floor, cap) * batch.column(0).to_numpy(zero_copy_only=False)) @ p if len(batch) else 0
            yield pa.record_batch([pa.array(range(k), pa.int32()), pa.array(total)], names=["k", "t"])

        got = {r[0]: r[1] for r in members.select("tokens", "posterior").mapInArrow(sums, "k int, t double").groupBy("k").agg(F.sum("t")).collect()}
        now = np.array([got.get(i, 0.0) for i in range(k)])
        mass = np.maximum(now, 1e-9) if mass is None else mass
        errors.append(float(np.abs(now - targets).sum() / max(1e-9, targets.sum())))
        if errors[-1] < tolerance or len(errors) > 3 and abs(errors[-4] - errors[-1]) < 1e-6:
            break
        steps = np.vstack([steps, (targets - now) / mass])
    return steps, errors


def memberships(docs: DataFrame, model: Membership, text_col: str = "text") -> DataFrame:
    """(tokens, posterior) of every document. Narrow."""
    def run(batches):
        for batch in batches:
            texts = pc.fill_null(batch.column(0), "").cast(pa.large_binary())
            for at, to in pieces(texts):
                found = [features(t.as_py()) for t in texts.slice(at, to - at)]
                p = model.posteriors(np.stack([f[0] for f in found]))
                yield pa.record_batch([pa.array([f[1] for f in found], pa.int64()), pa.array(list(p), pa.list_(pa.float64()))], names=["tokens", "posterior"])

    return docs.select(F.col(text_col).cast("string").alias("body")).mapInArrow(run, "tokens bigint, posterior array<double>")


class Mixture:
    """A fitted mixture: classifier, steps, bounds, and the relative error of each step."""

    def __init__(self, model: Membership, steps: np.ndarray, floor: float, cap: float, errors: list[float], targets: dict[str, float]):
        self.model, self.steps, self.floor, self.cap, self.errors, self.targets = model, steps, floor, cap, errors, targets

    def judge(self, texts) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        found = [features(t.as_py()) for t in texts]
        p = self.model.posteriors(np.stack([f[0] for f in found]))
        return replay(p, self.steps, self.floor, self.cap), p, np.array([f[1] for f in found], dtype=np.int64)


def fit(docs: DataFrame, labelled: DataFrame, weights: dict[str, float] | None, domain_col: str = "lang", growth: float = 1.0, floor: float = 0.0,
        cap: float = 8.0, id_col: str = "doc_id", text_col: str = "text") -> Mixture:
    """Fit rates whose expected domain totals are `growth` times the corpus, dealt by `weights` (equal if None).

    Domains that `weights` leaves out get weight zero.
    """
    model = fit_membership(docs, labelled, domain_col, id_col, text_col)
    members = settle(memberships(docs, model, text_col), "members")
    total = float(members.agg(F.coalesce(F.sum("tokens"), F.lit(0))).first()[0])
    share = np.array([(weights or dict.fromkeys(model.domains, 1.0)).get(d, 0.0) for d in model.domains])
    share = share / share.sum() if share.sum() > 0 else np.full(len(share), 1.0 / len(share))
    targets = growth * total * share
    steps, errors = fit_rates(members, targets, floor, cap)
    return Mixture(model, steps, floor, cap, errors, dict(zip(model.domains, targets.tolist())))


def _dealt(mixture: Mixture, texts: pa.Array, draws: np.ndarray):
    """(from, to, rate, posterior, tokens, copies) of runs of rows that hold about a megabyte of text."""
    texts = pc.fill_null(texts.cast(pa.string()), "").cast(pa.large_binary())
    for at, to in pieces(texts):
        rate, p, n = mixture.judge(texts.slice(at, to - at))
        yield at, to, rate, p, n, np.floor(rate + 1 - draws[at:to] - 1e-12).astype(np.int64)


def _draw(id_col: str, text_col: str):
    """A number in [0, 1) that a row's id and text decide."""
    both = F.xxhash64(F.coalesce(F.col(id_col).cast("string"), F.lit("")), F.col(text_col).cast("string"), F.lit("copies"))
    return F.pmod(both, F.lit(1 << 30)) / float(1 << 30)


def rates(docs: DataFrame, mixture: Mixture, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, tokens, domain, posterior, rate, copies) of every document. Narrow."""
    sent = docs.sparkSession.sparkContext.broadcast(mixture)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        for batch in batches:
            for at, to, rate, p, n, copies in _dealt(sent.value, batch.column(1), batch.column(2).to_numpy(zero_copy_only=False)):
                names = [sent.value.model.domains[i] for i in p.argmax(axis=1)]
                yield pa.record_batch([batch.column(0).slice(at, to - at), pa.array(n), pa.array(names), pa.array(list(p), pa.list_(pa.float64())), pa.array(rate),
                                       pa.array(copies.astype(np.int32))], names=["row_key", "tokens", "domain", "posterior", "rate", "copies"])

    found = docs.select(F.col(id_col).alias("row_key"), F.col(text_col).cast("string").alias("body"), _draw(id_col, text_col).alias("draw")).mapInArrow(
        run, f"row_key {kind}, tokens bigint, domain string, posterior array<double>, rate double, copies int")
    return found.withColumnRenamed("row_key", id_col)


def mix(docs: DataFrame, mixture: Mixture, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents repeated as often as their rates say, with all their columns, whatever those are called. Narrow."""
    sent = docs.sparkSession.sparkContext.broadcast(mixture)
    column, width, names = docs.columns.index(text_col), len(docs.columns), docs.columns

    def run(batches):
        for batch in batches:
            for at, to, _, _, _, copies in _dealt(sent.value, batch.column(column), batch.column(width).to_numpy(zero_copy_only=False)):
                part = batch.slice(at, to - at)
                part = pa.RecordBatch.from_arrays(part.columns[:width], names=names)
                for times in range(1, int(copies.max(initial=0)) + 1):  # one copy at a time: a batch never outgrows its input
                    yield part.filter(pa.array(copies >= times))

    return docs.select(*[F.col(f"`{c}`") for c in names], _draw(id_col, text_col).alias("draw " + " ".join(names))).mapInArrow(run, docs.schema)


#: Production target: shares of expected words by language.
TARGET = {"en": 0.5, "de": 0.2, "fr": 0.17, "es": 0.13}


def labelled_languages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids and languages of the rows that the label table lists: the labelled table of the classifier."""
    docs, labels = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    return docs.select("doc_id", "lang").join(labels.select("doc_id"), "doc_id", "left_semi")


def op6_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    mixture = fit(docs, labelled_languages(spark, sf_dir), TARGET)
    return rates(docs, mixture)
