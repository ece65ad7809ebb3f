"""Toxicity by multiple-instance learning.

A document is a bag of sentences.  A sentence has probability s = sigmoid(b + sum of the weights of its words), and the
document is toxic with the noisy-or 1 - prod(1 - s).  Weights are trained from document labels alone; the sentence
scores then tell where the offence is.

Words: runs of ASCII letters, digits and non-ASCII characters, lower-cased; they and some of their prefixes are
hashed to 2^18 features.  Sentences end at ``.``, ``!``, ``?`` or a line's end.  Training takes a bounded sample of labelled rows
(``max_docs`` per label, those of least hash, as long as they have ``max_bytes`` per label together; texts above ``max_chars`` bytes don't enter it); scoring covers every row and the
whole text.  Which prefixes are features and how strongly weights are held down is chosen by cross-validation over a part of
the sample, thus over training rows alone; every setting and fold is a task of its own, and the final fit is one too.  Defined cases: null, blank and wordless texts score 0; repeated rows score alike; labels that are null
don't train; with one label only, or none, all documents score that label's share (0 where there is none).
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from boundpath.llm.shared import read_table
from boundpath.llm.textkernel import Words, mix, powers, segment_sum, words

FEATURE_BITS = 18
#: Bounds of the sample, per label: documents, bytes of all their texts, bytes of one text.
MAX_DOCS, MAX_BYTES, MAX_CHARS = 4000, 24_000_000, 50_000
THRESHOLD = 0.3
#: Settings that cross-validation chooses from: bytes of the word prefixes that are features too (offensive stems take many
#: endings), and the squared-weight penalty per document.
PREFIXES = ((4, 5, 6, 7), (4,), ())
DECAYS = (5e-5, 1.5e-4, 5e-4)
FOLDS, FOLD_DOCS, FOLD_ROUNDS = 3, 1500, 120
ROUNDS = 300
MIN_DOCS = 3


@dataclass(frozen=True)
class Setting:
    prefixes: tuple[int, ...] = (4, 5, 6, 7)
    decay: float = 1.5e-4


def sentences(w: Words) -> np.ndarray:
    """The sentence of each word, numbered through the chunk; a document's first word starts a sentence."""
    stop = np.isin(w.data, np.frombuffer(b".!?\n", np.uint8))
    before = np.concatenate([[0], np.cumsum(stop)])[w.start]
    new = np.ones(len(w.start), bool)
    new[1:] = (before[1:] != before[:-1]) | (w.doc[1:] != w.doc[:-1])
    return np.cumsum(new) - 1


def features(w: Words, prefixes: tuple[int, ...], bits: int = FEATURE_BITS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The sentence of each word, a row of features for each word (itself and its prefixes), the document of each
    sentence.  A prefix that is not shorter than its word stands for the word's end and gets the last feature, which
    has no weight."""
    sentence = sentences(w)
    n = len(w.start)
    out = np.full((n, 1 + len(prefixes)), (1 << bits) - 1, np.int32)
    shift = np.uint64(64 - bits)
    out[:, 0] = w.hash >> shift
    power, inverse = powers(len(w.data) + 1)
    total = np.zeros(len(w.data) + 1, np.uint64)
    np.cumsum((w.data.astype(np.uint64) + np.uint64(1)) * power[: len(w.data)], out=total[1:])
    length = w.end - w.start
    for i, size in enumerate(prefixes):
        longer = np.flatnonzero(length > size)
        at = w.start[longer]
        out[longer, i + 1] = mix((total[at + size] - total[at]) * inverse[at], 40 + size) >> shift
    first = np.flatnonzero(np.diff(sentence, prepend=-1))
    return sentence, out, w.doc[first]


class NoisyOr:
    def __init__(self, weights: np.ndarray, bias: float, constant: float | None = None, prefixes: tuple[int, ...] = ()):
        self.weights, self.bias, self.constant, self.prefixes = weights, bias, constant, prefixes

    def sentence_logits(self, sentence, feature, n):
        return np.bincount(sentence, self.weights[feature].sum(axis=1), minlength=n) + self.bias

    def score(self, w: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(document scores, sentence scores, document of each sentence)."""
        counts = np.zeros(w.n_docs, np.int64)
        if not len(w.hash):
            return np.full(w.n_docs, self.constant or 0.0), np.zeros(0), np.zeros(0, np.int64)
        sentence, feature, doc = features(w, self.prefixes)
        z = self.sentence_logits(sentence, feature, len(doc))
        counts = np.bincount(doc, minlength=w.n_docs)
        safe = -np.logaddexp(0.0, z)  # ln(1 - s)
        score = -np.expm1(segment_sum(safe, counts))
        if self.constant is not None:
            score = np.full(w.n_docs, self.constant)
        return np.clip(score, 0.0, 1.0), 1.0 / (1.0 + np.exp(-np.clip(z, -700, 700))), doc


def train(texts, labels: list[int], totals: tuple[int, int] | None = None, setting: Setting = Setting(), rounds: int = ROUNDS, rate: float = 0.15, bits: int = FEATURE_BITS) -> NoisyOr:
    """Maximum likelihood of the document labels with Adam; totals: how many documents each label (0, 1) has of which these
    are a sample.

    texts: a list or an Arrow column.  Words of fewer than MIN_DOCS documents get no weight: they can't be told from chance."""
    y_all = np.array(labels, np.int64)
    column = pa.array(texts, pa.string()) if isinstance(texts, list) else texts
    if len(y_all) == 0 or y_all.min() == y_all.max():
        return NoisyOr(np.zeros(1 << bits), 0.0, float(y_all.mean()) if len(y_all) else 0.0)
    # two passes over chunks keep memory low: which features enough documents have, then the kept places alone
    held = np.zeros(1 << bits, np.int64)
    for w in words(column, "alnum"):
        if len(w.hash):
            sentence, feature, doc = features(w, setting.prefixes, bits)
            pairs = np.unique(((doc[sentence] << bits)[:, None] | feature).reshape(-1))
            held += np.bincount(pairs & ((1 << bits) - 1), minlength=1 << bits)
    held[-1] = 0
    names = np.flatnonzero(held >= MIN_DOCS)
    number = np.full(1 << bits, -1, np.int32)
    number[names] = np.arange(len(names), dtype=np.int32)
    blocks, docs, at = [], [], 0
    for w in words(column, "alnum"):
        if len(w.hash):
            sentence, feature, doc = features(w, setting.prefixes, bits)
            place = number[feature]
            row = np.broadcast_to(sentence[:, None], place.shape)[place >= 0].astype(np.int32)
            blocks.append((at, len(doc), row, place[place >= 0]))
            docs.append(doc + w.first)
            at += len(doc)
    doc = np.concatenate(docs) if docs else np.zeros(0, np.int64)
    n_docs, n_sent = len(y_all), len(doc)
    per_doc = np.bincount(doc, minlength=n_docs)
    share = y_all.mean()
    bias = np.log(max(share, 1e-3) / max(per_doc.mean(), 1.0)) - 1.0
    theta = np.zeros(len(names) + 1)
    theta[-1] = bias
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    stands = np.array([t / max(1, n) for t, n in zip(totals or (1, 1), np.bincount(y_all, minlength=2), strict=True)]) if totals else np.ones(2)
    weigh = stands[y_all]
    weigh = weigh / weigh.mean()
    for step in range(1, rounds + 1):
        z = np.full(n_sent, theta[-1])
        for lo, n, row, place in blocks:
            z[lo : lo + n] += np.bincount(row, theta[place], minlength=n)
        p = 1.0 / (1.0 + np.exp(-np.clip(z, -60, 60)))
        log_clean = np.bincount(doc, -np.logaddexp(0.0, z), minlength=n_docs)
        clean = np.exp(np.minimum(log_clean, -1e-9))
        pull = np.where(y_all == 1, -clean / np.maximum(1 - clean, 1e-9), 1.0) * weigh
        g_sent = p * pull[doc] / n_docs
        g = setting.decay * theta
        g[-1] = g_sent.sum()
        for lo, n, row, place in blocks:
            g[:-1] += np.bincount(place, g_sent[lo : lo + n][row], minlength=len(names))
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        theta -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    weights = np.zeros(1 << bits)
    weights[names] = theta[:-1]
    return NoisyOr(weights, float(theta[-1]), None, setting.prefixes)


def training_rows(docs: DataFrame, labels: DataFrame, max_docs: int = MAX_DOCS, max_chars: int = MAX_CHARS, max_bytes: int = MAX_BYTES) -> DataFrame:
    """A bounded sample of (text, toxic): per label, the rows of least hash.  docs and labels already hold training
    rows only."""
    known = labels.filter("toxic in (0, 1) and doc_id is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    rank = F.xxhash64("doc_id", F.lit(3))
    picked = None
    for value in (0, 1):
        part = known.filter(F.col("toxic") == value).orderBy(rank, "doc_id").limit(max_docs)
        picked = part if picked is None else picked.union(part)
    own = docs.select("doc_id", F.col("text").cast("string").alias("text")).filter(F.octet_length("text") <= max_chars)
    met = own.join(F.broadcast(picked), "doc_id").groupBy("doc_id", "text").agg(F.max("toxic").alias("toxic"))
    upto = F.sum(F.octet_length("text")).over(Window.partitionBy("toxic").orderBy(rank, "doc_id", "text"))
    return met.withColumn("upto", upto).filter(F.col("upto") <= max_bytes).orderBy("doc_id", "text").select("text", "toxic")


def log_loss(model: NoisyOr, column, labels: np.ndarray, totals) -> float:
    """Mean log loss; each label weighs as much as all its documents, of which these are a sample."""
    score = np.concatenate([model.score(w)[0] for w in words(column, "alnum")])
    score = np.clip(score, 1e-6, 1 - 1e-6)
    weigh = (np.array(totals) / np.maximum(1, np.bincount(labels, minlength=2)))[labels]
    return float(-np.average(np.where(labels == 1, np.log(score), np.log1p(-score)), weights=weigh))


def fold_loss(texts, labels: np.ndarray, totals, setting: Setting, fold: int) -> float:
    """Mean log loss on every FOLDS-th document of each label, after training on the others."""
    place = np.zeros(len(labels), np.int64)
    for value in (0, 1):
        mine = np.flatnonzero(labels == value)
        place[mine] = np.arange(len(mine))
    out = place % FOLDS == fold
    model = train(texts.filter(pa.array(~out)), labels[~out].tolist(), totals, setting, FOLD_ROUNDS)
    return log_loss(model, texts.filter(pa.array(out)), labels[out], totals) if out.any() else 0.0


def _in_task(spark, jobs: list[tuple], run) -> list:
    """``run(job)`` (bytes or number) of every job, each in a task of its own."""
    schema = "job int, found binary"

    def tasks(batches):
        for batch in batches:
            for i in batch.column(0).to_pylist():
                yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([pickle.dumps(run(*jobs[i]))], pa.binary())], names=["job", "found"])

    ids = spark.range(0, len(jobs), 1, len(jobs)).select(F.col("id").cast("int").alias("job"))
    found = {r.job: pickle.loads(r.found) for r in ids.mapInArrow(tasks, schema).collect()}
    return [found[i] for i in range(len(jobs))]


def choose_setting(spark, sample, totals: tuple[int, int]) -> tuple[Setting, dict]:
    """The setting of least mean loss over folds of (part of) the sample, a broadcast of (texts, labels); and all losses."""
    settings = [Setting(p, d) for p in PREFIXES for d in DECAYS]
    jobs = [(s, f) for s in settings for f in range(FOLDS)]

    def run(setting, number):
        texts, labels = sample.value
        first = np.sort(np.concatenate([np.flatnonzero(labels == v)[:FOLD_DOCS] for v in (0, 1)]))
        return fold_loss(texts.take(pa.array(first)), labels[first], totals, setting, number)

    losses = dict.fromkeys(settings, 0.0)
    for (setting, _), loss in zip(jobs, _in_task(spark, jobs, run), strict=True):
        losses[setting] += loss / FOLDS
    return min(settings, key=lambda s: (losses[s], settings.index(s))), losses


def _scorer(model):
    def run(batches):
        known: NoisyOr = model.value
        for batch in batches:
            ids = batch.column(0)
            for w in words(batch.column(1), "alnum"):
                score, per_sentence, doc = known.score(w)
                worst, place = np.zeros(w.n_docs), np.full(w.n_docs, -1, np.int64)
                if len(doc):
                    n = np.bincount(doc, minlength=w.n_docs)
                    start = np.cumsum(n) - n
                    order = np.lexsort((np.arange(len(doc)), -per_sentence, doc))
                    first = order[start[n > 0]]
                    place[n > 0] = first - start[n > 0]
                    worst[n > 0] = per_sentence[first]
                yield pa.RecordBatch.from_arrays(
                    [ids.slice(w.first, w.n_docs).cast(pa.int64()), pa.array(score), pa.array(place), pa.array(worst)], names=["doc_id", "score", "worst_sentence", "worst_score"]
                )

    return run


def fit(docs: DataFrame, labels: DataFrame, max_docs: int = MAX_DOCS, setting: Setting | None = None) -> NoisyOr:
    """The model of the best setting (or the one given), from the rows of ``docs`` that ``labels`` names."""
    spark = docs.sparkSession
    counts = dict(labels.filter("toxic in (0, 1)").groupBy("toxic").count().collect())
    totals = counts.get(0, 0), counts.get(1, 0)
    rows = training_rows(docs, labels, max_docs).toArrow()
    values = np.array(rows["toxic"].to_pylist(), np.int64)
    sample = spark.sparkContext.broadcast((pa.array(rows["text"].to_pylist(), pa.string()), values))
    if setting is None and len(set(values.tolist())) == 2:
        setting, _ = choose_setting(spark, sample, totals)
    setting = setting or Setting()

    def run(chosen):
        texts, known = sample.value
        model = train(texts, known.tolist(), totals, chosen)
        live = np.flatnonzero(model.weights)
        return live.astype(np.int32), model.weights[live], model.bias, model.constant

    live, weights, bias, constant = _in_task(spark, [(setting,)], run)[0]
    full = np.zeros(1 << FEATURE_BITS)
    full[live] = weights
    return NoisyOr(full, bias, constant, setting.prefixes)


def score_toxicity(docs: DataFrame, model: NoisyOr) -> DataFrame:
    """doc_id, score, worst_sentence (its number in the text, from 0; -1: none), worst_score for every row of ``docs``."""
    own = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sent = docs.sparkSession.sparkContext.broadcast(model)
    return own.mapInArrow(_scorer(sent), "doc_id bigint, score double, worst_sentence bigint, worst_score double")


def fold(doc_id, parts: int) -> F.Column:
    """crc32 of the id as text, modulo ``parts``."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % parts


def op6_toxicity(spark, sf_dir: str) -> DataFrame:
    docs, labels = read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels")
    held = F.coalesce(fold("doc_id", 4) == 2, F.lit(False))
    model = fit(docs, labels.filter(~held))
    out = score_toxicity(docs, model)
    return out.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"), "worst_sentence", "worst_score")


QUERIES = {"op6_toxicity": op6_toxicity}
