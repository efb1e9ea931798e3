"""Language identification: multinomial naive Bayes over hashed character n-grams.

Counts of hashed 1- to 3-grams per language are summed on the executors, for
``keep_identified`` over every training row, for ``identify`` over a
sample whose size is bounded by the parameter ``train_rows`` (rows are
taken by a hash of their content, so the sample is spread over the table).  The
log-probability matrix, ``languages x buckets``, is broadcast.  The grams of a
batch are one sparse list of (text, bucket) entries; each text sums the matrix
rows of its entries in numpy, whole texts always.

Defined results: null texts and texts without a letter (Unicode category L) are ``und`` with score 0;
rows without a label or text do not train; without any training row every text
is ``und``.  Ties go to the language that sorts first.  Extra columns are
ignored; rows are predicted one by one.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

BUCKET_BITS = 16
ORDERS = (1, 2, 3)
#: Bound on the rows that the classifier is fitted on.
TRAIN_ROWS = 20_000
#: Bound on the number of languages, and so on the broadcast matrix.
MAX_LANGUAGES = 1_000
UND = "und"

_LETTER = regex.compile(r"\p{L}")
_MIX = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D], np.uint32)
#: Code points that numpy handles at once.
_SLICE = 1 << 20
#: Code points above which a text is counted by itself, and of a batch of shorter ones.
_LONG = 1 << 15


def grams(codes: np.ndarray, order: int, bits: int = BUCKET_BITS) -> np.ndarray:
    """Bucket of every ``order``-gram of a code point array."""
    m = len(codes) - order + 1
    if m <= 0:
        return np.empty(0, np.uint32)
    acc = np.full(m, order, np.uint32)
    for j in range(order):
        acc = (acc ^ codes[j : j + m]) * _MIX[j % 3]
        acc ^= acc >> np.uint32(15)
    return acc >> np.uint32(32 - bits)


def codes_of(text: str) -> np.ndarray:
    return np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)


def counts_of(text: str, bits: int = BUCKET_BITS) -> np.ndarray:
    out, codes = np.zeros(1 << bits, np.int64), codes_of(text)
    for at in range(0, max(len(codes), 1), _SLICE):
        for o in ORDERS:  # a slice overlaps the next by the order
            out += np.bincount(grams(codes[at : at + _SLICE + o - 1], o, bits), minlength=1 << bits)
    return out


def counts_of_all(texts: list[str], bits: int = BUCKET_BITS) -> np.ndarray:
    """Sum of ``counts_of`` over ``texts``, short ones counted together."""
    out, at = np.zeros(1 << bits, np.int64), 0
    while at < len(texts):
        if len(texts[at]) > _LONG:
            out += counts_of(texts[at], bits)
            at += 1
            continue
        to, held = at, 0
        while to < len(texts) and len(texts[to]) <= _LONG and held <= 8 * _LONG:
            held += len(texts[to])
            to += 1
        codes = [codes_of(t) for t in texts[at:to]]
        sizes = np.array([len(c) for c in codes])
        left, all_codes = np.repeat(np.cumsum(sizes), sizes) - np.arange(sizes.sum()), np.concatenate(codes)
        for o in ORDERS:
            idx = grams(all_codes, o, bits)
            out += np.bincount(idx[left[: len(idx)] >= o], minlength=1 << bits)  # no gram reaches into the next text
        at = to
    return out


@dataclass
class Model:
    langs: list[str]
    log_prob: np.ndarray  # buckets x languages, float32
    log_prior: np.ndarray
    #: Smoothed gram count of each language.
    totals: np.ndarray
    #: Least mean log-probability of a gram, and its deviation; see ``bounded``.
    least: np.ndarray | None = None
    spread: np.ndarray | None = None

    def plausible(self, at: int, mean: float, n: int) -> bool:
        """Whether the mean log-probability of ``n`` grams is one of a language, at
        any length: a posterior only tells which language is less unlikely."""
        return mean >= self.least[at] - 2 * self.spread[at] / np.sqrt(n)

    def sums(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Log-probability of each text's grams by language, and their number."""
        bits = self.log_prob.shape[0].bit_length() - 1
        total, n = np.zeros((len(texts), len(self.langs))), np.zeros(len(texts), np.int64)
        at = 0
        while at < len(texts):
            if len(texts[at]) > _LONG:  # one dense row
                counts = counts_of(texts[at], bits)
                total[at], n[at] = counts.astype(np.float64) @ self.log_prob, counts.sum()
                at += 1
                continue
            to, held = at, 0
            while to < len(texts) and len(texts[to]) <= _LONG and held <= _LONG:
                held += len(texts[to])
                to += 1
            codes = [codes_of(t) for t in texts[at:to]]
            sizes = np.array([len(c) for c in codes])
            ends, all_codes = np.cumsum(sizes), np.concatenate(codes)
            for o in ORDERS:
                idx = grams(all_codes, o, bits)
                of = np.repeat(np.arange(to - at), sizes)[: len(idx)]
                inside = np.arange(len(idx)) + o <= ends[of]  # no gram reaches into the next text
                idx, of = idx[inside], of[inside]
                if not len(idx):
                    continue
                starts = np.flatnonzero(np.concatenate(([True], of[1:] != of[:-1])))
                total[at + of[starts]] += np.add.reduceat(self.log_prob[idx], starts, axis=0, dtype=np.float64)
                n[at + of[starts]] += np.diff(np.append(starts, len(idx)))
            at = to
        return total, n

    def scores(self, texts: list[str | None]) -> list[tuple[str, float, bool]]:
        """Language, posterior, and whether the text is plausible in it (true
        where no bounds were learned)."""
        out = [(UND, 0.0, False)] * len(texts)
        at = [i for i, t in enumerate(texts) if t and self.langs and _LETTER.search(t)]
        total, n = self.sums([texts[i] for i in at])
        for i, row, m in zip(at, total, n.tolist(), strict=True):
            full = row + self.log_prior
            best = int(np.argmax(full))
            fits = self.least is None or self.plausible(best, row[best] / m, m)
            out[i] = self.langs[best], float(1.0 / np.exp(full - full[best]).sum()), fits
        return out


def _sample(train: DataFrame, train_rows: int | None) -> DataFrame:
    """The rows that train; all of them without a bound."""
    rows = train.filter("text IS NOT NULL AND lang IS NOT NULL").select("text", "lang")
    if train_rows is None:
        return rows
    total = rows.count()
    if total > train_rows:
        parts = 1 << 20
        rows = rows.filter(F.pmod(F.xxhash64("text"), F.lit(parts)) < int(parts * train_rows / total))
    return rows


def fit(train: DataFrame, bits: int = BUCKET_BITS, train_rows: int | None = TRAIN_ROWS, alpha: float = 0.5) -> Model:
    """Fit on rows ``(text, lang)`` of ``train``; both must be non-null."""
    common.tune_arrow(train.sparkSession)
    rows = _sample(train, train_rows)
    known = rows.select("lang").distinct().limit(MAX_LANGUAGES + 1).count()
    if known > MAX_LANGUAGES:  # before anything of that size is gathered
        raise ValueError(f"more than {MAX_LANGUAGES} languages, the bound of the broadcast matrix")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, np.ndarray] = {}
        docs: dict[str, int] = {}
        for b in batches:
            by: dict[str, list[str]] = {}
            for text, lang in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if _LETTER.search(text):
                    by.setdefault(lang, []).append(text)
            for lang, texts in by.items():
                if lang not in held:
                    held[lang] = np.zeros(1 << bits, np.int64)
                held[lang] += counts_of_all(texts, bits)
                docs[lang] = docs.get(lang, 0) + len(texts)
        for lang, c in held.items():
            at = np.flatnonzero(c)
            cols = [pa.array([lang] * (len(at) + 1)), pa.array(np.append(at, -1).astype(np.int32)), pa.array(np.append(c[at], docs[lang]))]
            yield pa.RecordBatch.from_arrays(cols, ["lang", "bucket", "n"])

    found = rows.mapInArrow(run, "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))
    table = found.toPandas()  # at most languages x (buckets + 1) rows
    langs = sorted(table["lang"].unique().tolist())
    counts, prior = np.zeros((1 << bits, len(langs))), np.zeros(len(langs))
    col = table["lang"].map({x: i for i, x in enumerate(langs)}).to_numpy(dtype=int)
    at, n = table["bucket"].to_numpy(), table["n"].to_numpy()
    inside = at >= 0
    counts[at[inside], col[inside]] = n[inside]
    prior[col[~inside]] = n[~inside]
    smooth = counts + alpha
    return Model(langs, np.log(smooth / smooth.sum(0)).astype(np.float32), np.log(prior / max(prior.sum(), 1)), smooth.sum(0))


def bounded(model: Model, train: DataFrame, train_rows: int | None = TRAIN_ROWS, alpha: float = 0.5) -> Model:
    """``model`` with its bounds learned from the rows that it was fitted on.

    Each row is scored as if it had not trained.  The bound of a language lies
    below the lowest hundredth of its rows by half the distance from there to
    the median; a short text gets two deviations of its mean besides."""
    if not model.langs:
        return model
    sent = train.sparkSession.sparkContext.broadcast(pickle.dumps(model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = pickle.loads(sent.value)
        bits = m.log_prob.shape[0].bit_length() - 1
        for b in batches:
            out = []
            for text, lang in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if _LETTER.search(text):
                    i = m.langs.index(lang)
                    if len(text) > _LONG:
                        own = counts_of(text, bits)
                        at = np.flatnonzero(own)
                        n = own[at]
                    else:
                        codes = codes_of(text)
                        at, n = np.unique(np.concatenate([grams(codes, o, bits) for o in ORDERS]), return_counts=True)
                    rest = np.maximum(np.exp(m.log_prob[at, i].astype(np.float64)) * m.totals[i] - n, alpha)
                    out.append((lang, float((n * np.log(rest / (m.totals[i] - n.sum()))).sum() / n.sum())))
            langs, means = zip(*out, strict=True) if out else ((), ())
            yield pa.RecordBatch.from_arrays([pa.array(langs, pa.string()), pa.array(means, pa.float64())], ["lang", "mean"])

    means = _sample(train, train_rows).mapInArrow(run, "lang string, mean double")
    found = {
        r["lang"]: r["q"] for r in means.groupBy("lang").agg(F.percentile_approx("mean", [0.01, 0.5], 10_000).alias("q")).collect()
    }
    low, mid = (np.array([found[x][j] for x in model.langs]) for j in (0, 1))
    log_p = model.log_prob.astype(np.float64)
    p = np.exp(log_p)
    return replace(model, least=low - (mid - low) / 2, spread=np.sqrt((p * log_p**2).sum(0) - (p * log_p).sum(0) ** 2))


def predict(docs: DataFrame, model: Model, key: list[str]) -> DataFrame:
    """Columns ``key`` of ``docs`` with lang_pred and score of every whole text."""
    spark = docs.sparkSession
    common.tune_arrow(spark)
    sent = spark.sparkContext.broadcast(pickle.dumps(model))
    base = docs.select(*key, "text")
    fields = [f for f in base.schema.fields if f.name != "text"]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in fields)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = pickle.loads(sent.value)
        for b in batches:
            got = m.scores(b.column(len(key)).to_pylist())
            cols = [b.column(i) for i in range(len(key))]
            yield pa.RecordBatch.from_arrays(
                [*cols, pa.array([x[0] for x in got], pa.string()), pa.array([x[1] for x in got], pa.float64())],
                [*key, "lang_pred", "score"],
            )

    return base.mapInArrow(run, f"{schema}, lang_pred string, score double")


def is_held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))


def identify(docs: DataFrame, train_rows: int = TRAIN_ROWS) -> DataFrame:
    """doc_id, held_out, lang_pred, score; trained on the rows not held out."""
    model = fit(docs.filter(~is_held_out()), train_rows=train_rows)
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumn("held_out", is_held_out())
    return predict(keyed, model, ["doc_id", "held_out"])


def keep_identified(docs: DataFrame, min_score: float = 0.5, train_rows: int | None = None) -> DataFrame:
    """``docs`` without the rows whose language is rejected: ``und``, a
    posterior under ``min_score``, or grams too unlikely in every language
    learned.  All columns of ``docs`` stay.  Counts and bounds come from every
    row that is not held out, unless ``train_rows`` bounds them."""
    spark = docs.sparkSession
    train = docs.filter(~is_held_out())
    model = bounded(fit(train, train_rows=train_rows), train, train_rows)
    sent = spark.sparkContext.broadcast(pickle.dumps(model))
    at = docs.columns.index("text")

    def run(batches):
        m = pickle.loads(sent.value)
        for b in batches:
            kept = [lang != UND and score >= min_score and fits for lang, score, fits in m.scores(b.column(at).to_pylist())]
            yield b.filter(pa.array(kept, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
