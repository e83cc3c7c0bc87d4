"""Toxicity by a linear-chain conditional random field over words.

Token labels come from the labelled documents: inside documents marked toxic, a word is labelled toxic if it, or its
stem of four or five letters, is far commoner in toxic than in clean documents.  The chain has two states; a word's
emission depends on the word, its stems and its endings, so it is computed once per distinct word.  Forward-backward
marginals are exact over whole documents: chunks of the chain are composed as two-by-two matrices and scanned.  A
logistic calibration turns a document's marginals into its score; words with a marginal of one half or more are the
offending spans (code points, end exclusive).

Training uses a bounded, documented sample of labelled rows: about `per_class` documents of each label and no more than about
`most_bytes` of text of each, chosen by a hash of the id; and of each of those at most HOT windows of WINDOW words with a toxic
word and COLD without one (a document's last window may be shorter, so short documents train too).  The words that are
toxic, and the calibration, come from the sample's whole texts; scoring covers every document whole.  Defined results: null counts as empty; a text without words has all-zero evidence
and gets the calibrated score of that; repeated rows are scored alike; without both labels in the sample every score is
the labelled share of toxic rows (0.0 with no labels at all); extra columns are ignored.
"""

from __future__ import annotations

import itertools
import math
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pandas.util import hash_array
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paircuration.llm.common import fit_logistic, fold_of, pieces, sigmoid

SLOTS = 1 << 18
PER_CLASS, MOST_BYTES = 3000, 32 << 20
WINDOW, HOT, COLD = 32, 8, 4
_WORD = re.compile(r"\w+")
_CHAIN = 128
_CACHE = 200_000


def _features(words: list[str]) -> np.ndarray:
    """Weight slots of each word's features: the word, its first four, five and six letters, its last four and three."""
    low = [w.lower() for w in words]
    cuts = (low, [w[:4] for w in low], [w[:5] for w in low], [w[:6] for w in low], [w[-4:] for w in low], [w[-3:] for w in low])
    hashed = [hash_array(np.array(c, dtype=object), categorize=False) * np.uint64(2 * i + 0x9E3779B97F4A7C15) for i, c in enumerate(cuts)]
    return (np.stack(hashed, axis=1) >> np.uint64(40)).astype(np.int64) & (SLOTS - 1)


class Tagger:
    """CRF weights, the per-word emission cache, and the document calibration."""

    def __init__(self, weights: np.ndarray, bias: float, moves: np.ndarray, calibration: np.ndarray | None, base: float):
        self.weights, self.bias, self.moves, self.calibration, self.base = weights, bias, moves, calibration, base
        self.cache: dict[str, float] = {}

    def __getstate__(self):
        return self.__dict__ | {"cache": {}}

    def _look(self, words: list[str]) -> np.ndarray:
        """Emissions of distinct words."""
        if len(self.cache) >= _CACHE:  # common words came early and stay
            self.cache = dict(itertools.islice(self.cache.items(), _CACHE // 2))
        found = np.fromiter(map(self.cache.get, words, itertools.repeat(np.nan)), np.float64, len(words))
        lacking = np.flatnonzero(np.isnan(found))
        for at in range(0, len(lacking), 1 << 14):
            part = lacking[at : at + (1 << 14)]
            fresh = [words[i] for i in part.tolist()]
            found[part] = self.weights[_features(fresh)].sum(axis=1) + self.bias
            self.cache.update(zip(fresh, found[part].tolist()))
        return found

    def marginals(self, lengths: np.ndarray, emission: np.ndarray) -> np.ndarray:
        """P(toxic) of every word, for several documents laid end to end."""
        return chain_marginals(lengths, emission, self.moves)

    def evidence(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Per document three aggregates of its marginals; all marginals; words per document."""
        words = [_WORD.findall(t) for t in texts]
        lengths = np.fromiter(map(len, words), np.int64, len(words))
        places = dict.fromkeys(itertools.chain.from_iterable(words))
        distinct = self._look(list(places))
        places.update(zip(places, range(len(places))))
        emission = distinct[np.fromiter(map(places.__getitem__, itertools.chain.from_iterable(words)), np.int64, int(lengths.sum()))]
        p = self.marginals(lengths, emission)
        owner = np.repeat(np.arange(len(texts)), lengths)
        mass = np.bincount(owner, weights=p, minlength=len(texts))
        top = np.zeros(len(texts))
        np.maximum.at(top, owner, p)
        return np.stack([np.log1p(mass), top, np.log1p(200 * mass / np.maximum(1, lengths))], axis=1), p, lengths

    def scores(self, evidence: np.ndarray) -> np.ndarray:
        if self.calibration is None:
            return np.full(len(evidence), self.base)
        return sigmoid(evidence @ self.calibration[:-1] + self.calibration[-1])


def chain_marginals(lengths: np.ndarray, emission: np.ndarray, moves: np.ndarray) -> np.ndarray:
    """Exact forward-backward for two states over independent chains laid end to end.

    The words are cut into rows of equal length, padded with neutral words; a chain's first word restarts, with all moves
    equal.  A message is the odds of state 1.  The product of a row's transition matrices is formed for all rows at once
    and serves both directions: the rows' ends are scanned in order, and the messages inside all rows follow at once again.
    """
    total = int(lengths.sum())
    if not total:
        return np.zeros(0)
    rows = -(-total // _CHAIN)
    size = rows * _CHAIN
    odds, restart = np.ones(size), np.zeros(size, dtype=bool)
    odds[:total] = np.exp(np.clip(emission, -60, 60))
    restart[total:] = True
    restart[np.concatenate([[0], np.cumsum(lengths)[:-1]])[lengths > 0]] = True
    e = np.ascontiguousarray(odds.reshape(rows, _CHAIN).T)
    again = np.ascontiguousarray(restart.reshape(rows, _CHAIN).T)
    m00, m01, m10, m11 = (np.where(again, 1.0, m) for m in np.asarray(moves, dtype=np.float64).ravel())

    a, d = np.ones(rows), np.ones(rows)  # [[a, b], [c, d]]: from the state before the row to the state at its end
    b, c = np.zeros(rows), np.zeros(rows)
    for t in range(_CHAIN):
        a, b = a * m00[t] + b * m10[t], (a * m01[t] + b * m11[t]) * e[t]
        c, d = c * m00[t] + d * m10[t], (c * m01[t] + d * m11[t]) * e[t]
        if t % 4 == 3:
            scale = 1.0 / (a + b + c + d)
            a, b, c, d = a * scale, b * scale, c * scale, d * scale
    into, after = np.empty(rows), np.empty(rows)
    product = list(zip(a.tolist(), b.tolist(), c.tolist(), d.tolist()))
    f = 1.0
    for r, (pa_, pb, pc_, pd) in enumerate(product):
        into[r], f = f, (pb + f * pd) / (pa_ + f * pc_)
    g = 1.0
    for r in range(rows - 1, -1, -1):
        pa_, pb, pc_, pd = product[r]
        after[r], g = g, (pc_ + pd * g) / (pa_ + pb * g)

    joint = np.empty((_CHAIN, rows))
    for t in range(_CHAIN):
        into = e[t] * (m01[t] + into * m11[t]) / (m00[t] + into * m10[t])
        joint[t] = into
    for t in range(_CHAIN - 1, -1, -1):
        joint[t] *= after
        g = e[t] * after
        after = (m10[t] + m11[t] * g) / (m00[t] + m01[t] * g)
    joint /= 1.0 + joint
    return joint.T.ravel()[:total]


def _sketch(words: list[str]) -> tuple[int, ...]:
    """The three smallest hashes of three-word runs: alike in near copies, not in texts that share one passage."""
    return tuple(sorted({zlib.crc32(" ".join(words[i : i + 3]).encode()) for i in range(max(1, len(words) - 2))})[:3])


def _toxic_words(docs: list[tuple[list[str], int]]) -> tuple[set[str], set[str]]:
    """Words and stems far commoner in toxic documents; families of near copies count once."""
    seen: set[tuple[tuple[int, ...], int]] = set()
    found = {0: Counter(), 1: Counter()}
    sizes = Counter()
    for words, toxic in docs:
        mark = (_sketch(words), toxic)
        if mark in seen or not words:
            continue
        seen.add(mark)
        sizes[toxic] += 1
        found[toxic].update({x for w in set(words) for x in (f"w{w}", f"4{w[:4]}" if len(w) > 5 else "", f"5{w[:5]}" if len(w) > 6 else "") if x})
    least = max(3, sizes[1] // 250)
    chosen = set()
    for name, t in found[1].items():
        c = found[0].get(name, 0)
        odds = math.log((t + 0.5) / (sizes[1] + 1)) - math.log((c + 0.5) / (sizes[0] + 1))
        if t >= least and odds >= math.log(15):
            chosen.add(name)
    return {x[1:] for x in chosen if x[0] == "w"}, {x[1:] for x in chosen if x[0] != "w"}


def train_crf(docs: list[tuple[list[str], int]], epochs: int = 4, rate: float = 0.3, l2: float = 1e-4, seed: int = 11):
    """Token labels by weak supervision, then AdaGrad ascent on the conditional likelihood of windows."""
    bad, stems = _toxic_words(docs)
    ids: dict[str, int] = {}
    by_size: dict[int, tuple[list, list]] = {}
    rng = np.random.default_rng(seed)
    for words, toxic in docs:
        marks = np.array([toxic == 1 and (w in bad or w[:4] in stems and len(w) > 5 or w[:5] in stems and len(w) > 6) for w in words], dtype=bool)
        starts = range(0, len(words), WINDOW)
        hot = [s for s in starts if marks[s : s + WINDOW].any()][:HOT]
        cold = [s for s in starts if not marks[s : s + WINDOW].any()]
        for s in hot + [cold[i] for i in rng.permutation(len(cold))[: COLD // 2 if toxic else COLD]]:
            rows, tags = by_size.setdefault(len(marks[s : s + WINDOW]), ([], []))
            rows.append([ids.setdefault(w, len(ids)) for w in words[s : s + WINDOW]])
            tags.append(marks[s : s + WINDOW])
    weights, bias, moves = np.zeros(SLOTS), -2.0, np.zeros((2, 2))
    if not by_size:
        return weights, bias, np.exp(moves)
    table = _features(list(ids))
    windows = {k: (np.array(r), np.array(t, dtype=np.float64)) for k, (r, t) in sorted(by_size.items())}
    grad_w, grad_b, grad_m = np.full(SLOTS, 1e-6), 1e-6, np.full((2, 2), 1e-6)
    for _ in range(epochs):
        batches = [(k, at) for k, (r, _) in windows.items() for at in np.array_split(rng.permutation(len(r)), max(1, len(r) // 256))]
        for k, at in (batches[i] for i in rng.permutation(len(batches))):
            rows, tags = windows[k]
            x, y = table[rows[at]], tags[at]
            n = 256 if len(at) < 256 else len(at)  # a small batch weighs by its windows
            emission = weights[x].sum(axis=2) + bias
            p = chain_marginals(np.full(len(at), k), emission.ravel(), np.exp(moves)).reshape(len(at), k)
            gap = (y - p) / n
            g = np.bincount(x.ravel(), weights=np.repeat(gap.ravel(), x.shape[2]), minlength=SLOTS) - l2 * len(at) / n * weights
            grad_w += g * g
            weights += rate * g / np.sqrt(grad_w)
            gb = gap.sum()
            grad_b += gb * gb
            bias += rate * gb / math.sqrt(grad_b)
            want = np.array([[((1 - y[:, :-1]) * (1 - y[:, 1:])).sum(), ((1 - y[:, :-1]) * y[:, 1:]).sum()], [(y[:, :-1] * (1 - y[:, 1:])).sum(), (y[:, :-1] * y[:, 1:]).sum()]])
            gm = (want - pair_expectations(emission, moves) - l2 * len(at) * moves) / n
            grad_m += gm * gm
            moves += rate * gm / np.sqrt(grad_m)
    return weights, bias, np.exp(moves)


def pair_expectations(emission: np.ndarray, moves: np.ndarray) -> np.ndarray:
    """Expected transition counts of equally long chains (rows of `emission`)."""
    n, size = emission.shape
    e = np.stack([np.zeros_like(emission), emission], axis=2)
    alpha, beta = np.empty((n, size, 2)), np.zeros((n, size, 2))
    alpha[:, 0] = e[:, 0]
    for t in range(1, size):
        alpha[:, t] = np.logaddexp.reduce(alpha[:, t - 1, :, None] + moves[None], axis=1) + e[:, t]
    for t in range(size - 2, -1, -1):
        beta[:, t] = np.logaddexp.reduce(moves[None] + (e[:, t + 1] + beta[:, t + 1])[:, None, :], axis=2)
    whole = np.logaddexp.reduce(alpha[:, -1], axis=1)
    joint = alpha[:, :-1, :, None] + moves[None, None] + (e[:, 1:] + beta[:, 1:])[:, :, None, :] - whole[:, None, None, None]
    return np.exp(joint).sum(axis=(0, 1))


def fit(docs: DataFrame, labels: DataFrame, label_col: str = "toxic", id_col: str = "doc_id", text_col: str = "text",
        per_class: int = PER_CLASS, most_bytes: int = MOST_BYTES) -> Tagger:
    """Train on a sample of documents outside the held-out fold.

    A row is in it if the hash of its id is below its label's share, which expects `per_class` rows and at most `most_bytes`;
    sizes are measured in the executors, and only the sample's texts reach the driver.
    """
    marked = labels.select(F.col(id_col).alias("row_key"), F.col(label_col).cast("int").alias("label")).filter(
        "row_key IS NOT NULL AND label IN (0, 1)").filter(fold_of(F.col("row_key")) != 1)
    body = F.col(text_col).cast("string")
    sized = docs.select(F.col(id_col).alias("row_key"), F.coalesce(F.octet_length(body), F.lit(0)).alias("bytes")).join(marked, "row_key")
    held = {r[0]: (r[1], r[2]) for r in sized.groupBy("label").agg(F.count(F.lit(1)), F.sum("bytes")).collect()}
    share = {k: min(1.0, per_class / n, most_bytes / max(1, size)) for k, (n, size) in held.items()}
    draw = F.pmod(F.xxhash64("row_key", F.lit("toxicity")), F.lit(1 << 30)) / float(1 << 30)
    chosen = marked.filter(draw < F.when(F.col("label") == 1, share.get(1, 1.0)).otherwise(share.get(0, 1.0)))  # about 2 * per_class ids
    shares = {k: n for k, (n, _) in held.items()}
    rows = docs.select(F.col(id_col).alias("row_key"), body.alias("body")).join(F.broadcast(chosen), "row_key").select("body", "label").toPandas()
    texts, y = [t or "" for t in rows["body"]], rows["label"].to_numpy(np.int64)
    total = sum(shares.values())
    base = shares.get(1, 0) / total if total else 0.0
    order = np.array(sorted(range(len(texts)), key=lambda i: zlib.crc32(texts[i].encode())), dtype=np.int64)
    texts, y = [texts[i] for i in order], y[order]
    if len(set(y.tolist())) < 2:
        return Tagger(np.zeros(SLOTS), -6.0, np.ones((2, 2)), None, base)
    pool: dict[str, str] = {}  # one string object per distinct word
    lowered = (([pool.setdefault(w, w) for w in _WORD.findall(t.lower())], int(k)) for t, k in zip(texts, y))
    tagger = Tagger(*train_crf(list(lowered)), None, base)
    found = np.concatenate([tagger.evidence(texts[i : i + 200])[0] for i in range(0, len(texts), 200)])
    weight = np.where(y == 1, base / max(1e-9, y.mean()), (1 - base) / max(1e-9, 1 - y.mean()))
    tagger.calibration = fit_logistic(found, y.astype(float), weight, l2=0.1)
    return tagger


def _spans(text: str, p: np.ndarray) -> list[dict]:
    return [{"start": m.start(), "end": m.end(), "p": float(q)} for m, q in zip(_WORD.finditer(text), p) if q >= 0.5]


def score(docs: DataFrame, tagger: Tagger, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score, spans): narrow, every word of every document."""
    sent = docs.sparkSession.sparkContext.broadcast(tagger)
    kind = docs.schema[id_col].dataType.simpleString()
    span = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("p", pa.float64())]))

    def run(batches):
        for batch in batches:
            for at, to in pieces(batch.column(1)):
                part = batch.slice(at, to - at)
                texts = [t or "" for t in part.column(1).to_pylist()]
                evidence, p, lengths = sent.value.evidence(texts)
                ends = np.cumsum(lengths)
                spans = [_spans(t, p[b - n : b]) if (p[b - n : b] >= 0.5).any() else [] for t, n, b in zip(texts, lengths, ends)]
                yield pa.record_batch([part.column(0), pa.array(sent.value.scores(evidence)), pa.array(spans, span)], names=["row_key", "score", "spans"])

    found = docs.select(F.col(id_col).alias("row_key"), F.col(text_col).cast("string").alias("body")).mapInArrow(
        run, f"row_key {kind}, score double, spans array<struct<start:int,end:int,p:double>>")
    return found.withColumnRenamed("row_key", id_col)


def remove_toxic(docs: DataFrame, tagger: Tagger, threshold: float = 0.7, text_col: str = "text") -> DataFrame:
    """Documents that score below the threshold, with all their columns. Narrow."""
    sent = docs.sparkSession.sparkContext.broadcast(tagger)
    column = docs.columns.index(text_col)

    def run(batches):
        for batch in batches:
            for at, to in pieces(batch.column(column)):
                part = batch.slice(at, to - at)
                evidence, _, _ = sent.value.evidence([t or "" for t in part.column(column).to_pylist()])
                yield part.filter(pa.array(sent.value.scores(evidence) < threshold))

    return docs.mapInArrow(run, docs.schema)


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    found = score(docs, fit(docs, labels))
    return found.select("doc_id", (fold_of(F.col("doc_id")) == 1).alias("held_out"), "score",
                        (F.col("score") >= 0.7).cast("int").alias("predicted"), F.size("spans").alias("n_spans"))
