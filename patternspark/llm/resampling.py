"""Quality selection by importance resampling.

Two generative models over hashed n-grams, one of target text (labelled good), one of the raw corpus; a text's
importance weight is the ratio of its probabilities under them. Standard Gumbel noise on the log weights and the k
largest keys draw k documents without replacement, each next one in proportion to the weights of those that are left.

N-grams are tokens (runs of letters and digits, or of punctuation; case matters) and pairs of neighbours. A pair is
hashed by the difference of its tokens' hashes: pairs of different tokens spread over all buckets, and a token that
follows itself is the same n-gram whichever token it is. Hashing is vectorised over the bytes of many texts: a token's
hash comes from two prefix sums.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import add_columns, cut, quoted, slices

BUCKETS = 10_000
#: Labelled documents that the target model and the share of good ones are fitted on, about.
SAMPLE = 4096
SMOOTH = 0.5
_CHUNK = 1 << 20
_MULT = np.uint64(0xD6E8FEB86659FD93)
_KIND = np.ones(256, dtype=np.uint8)  # 1 punctuation, 0 space, 2 letter or digit or part of a longer character
_KIND[[9, 10, 11, 12, 13, 32]] = 0
for _lo, _hi in ((48, 58), (65, 91), (97, 123), (128, 256)):
    _KIND[_lo:_hi] = 2
_ODD_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_ODD = np.uint64(0x9E3779B97F4A7C15)


def _powers(base: np.uint64, n: int) -> np.ndarray:
    out = np.full(n + 1, base, dtype=np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


_UP, _DOWN = _powers(_ODD, _CHUNK), _powers(_ODD_INVERSE, _CHUNK)


def token_hashes(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and 64-bit hash of each token in bytes (at most _CHUNK of them)."""
    kind = _KIND[raw]
    edge = np.flatnonzero(np.diff(kind, prepend=np.uint8(255)))
    ends = np.append(edge[1:], len(raw))
    token = kind[edge] > 0
    starts, ends = edge[token], ends[token]
    sums = np.zeros(len(raw) + 1, dtype=np.uint64)
    np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * _UP[:len(raw)], out=sums[1:])
    h = (sums[ends] - sums[starts]) * _DOWN[starts]
    h ^= h >> np.uint64(29)
    return starts, h * _MULT


def features(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Text number and bucket of every n-gram of the texts."""
    who, what = [], []
    chunk, owners, held = [], [], 0

    def flush() -> None:
        nonlocal held
        if not chunk:
            return
        raw = np.frombuffer(b"".join(chunk), dtype=np.uint8)
        starts, h = token_hashes(raw)
        bounds = np.cumsum([len(c) for c in chunk])
        own = np.array(owners)[np.searchsorted(bounds, starts, side="right")]
        pair = own[1:] == own[:-1]
        diff = ((h[1:] - h[:-1])[pair] * _MULT) ^ np.uint64(0x5851F42D4C957F2D)
        who.append(np.concatenate([own, own[1:][pair]]))
        what.append(np.concatenate([h >> np.uint64(33), diff >> np.uint64(33)]) % np.uint64(BUCKETS))
        chunk.clear(), owners.clear()
        held = 0

    for i, t in enumerate(texts):
        raw = (t or "").encode("utf-8", "surrogatepass") + b"\n"
        while len(raw) > _CHUNK:  # a very long text goes in parts that end at white space where there is one
            at = max(raw.rfind(b" ", 0, _CHUNK), raw.rfind(b"\n", 0, _CHUNK)) + 1 or _CHUNK
            flush()
            chunk.append(raw[:at]), owners.append(i)
            flush()
            raw = raw[at:]
        if held + len(raw) > _CHUNK:
            flush()
        chunk.append(raw), owners.append(i)
        held += len(raw)
    flush()
    if not who:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    return np.concatenate(who), np.concatenate(what).astype(np.int64)


@dataclass
class Model:
    """``ratio``: log of target over raw probability of each bucket; ``share``: of all documents, how many to draw."""

    ratio: np.ndarray
    share: float = 1.0

    def score(self, texts: list[str | None]) -> np.ndarray:
        """Log importance weight of each text (0 for texts without n-grams)."""
        who, what = features(texts)
        return np.bincount(who, self.ratio[what], minlength=len(texts)).astype(np.float64)  # of nothing: integers otherwise


def _bucket_counts(texts: DataFrame) -> np.ndarray:
    """How often each bucket occurs; at most BUCKETS rows reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(BUCKETS, dtype=np.int64)
        for whole in batches:
            for b in slices(whole, 0):
                total += np.bincount(features(b.column(0).to_pylist())[1], minlength=BUCKETS)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["b", "n"])

    got = texts.mapInArrow(run, "b long, n long").groupBy("b").agg(F.sum("n").alias("n")).toPandas()
    out = np.zeros(BUCKETS)
    out[got["b"]] = got["n"]
    return out


def fit(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", sample: int = SAMPLE) -> Model:
    """Raw model of all ``docs``, target model of the good ones among about ``sample`` labelled documents.

    The share to draw is that of good documents among the sampled labels plus one standard error of it, so that the
    sample's error does not cost good documents. The sample depends on ids alone; rows of ``labels`` with a null id or
    label are ignored, of several labels of one id the greatest counts. Null texts count as empty, copies each for
    themselves, very long texts are read whole, other columns are ignored. Without good labels (also: no documents)
    every weight is 1 and the share is 1.
    """
    known = labels.select(quoted(id_col).alias("id"), quoted(label_col).alias("label")).where("id is not null and label is not null").groupBy("id").agg(F.max("label").alias("label"))
    n = known.count()
    drawn = cut(known.where((F.xxhash64(F.lit(3), F.col("id")) / F.lit(2.0**64)) + 0.5 <= sample / max(n, 1)), "drawn-labels")  # about ``sample`` ids
    good, of = drawn.agg(F.coalesce(F.sum((F.col("label") == 1).cast("int")), F.lit(0)), F.count(F.lit(1))).first()
    plain = docs.select(quoted(id_col).alias("id"), quoted(text_col).alias("text"))
    raw = _bucket_counts(plain.select("text"))
    target = _bucket_counts(plain.join(F.broadcast(drawn.where("label = 1").select("id")), "id", "left_semi").select("text"))
    if not target.sum():
        return Model(np.zeros(BUCKETS))
    share = good / of
    share = min(1.0, share + (share * (1 - share) / of) ** 0.5)
    return Model(np.log((target + SMOOTH) / (target + SMOOTH).sum()) - np.log((raw + SMOOTH) / (raw + SMOOTH).sum()), share)


def score(docs: DataFrame, model: Model, *, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """The columns ``keep`` (default: all) and ``log_weight``, which replaces an input column of that name.

    Null and empty texts have weight 1 (its log is 0). Texts are read whole.
    """
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        own = shipped.value
        return lambda texts: [pa.array(np.round(own.score(texts), 6))]

    keep = [c for c in (docs.columns if keep is None else keep) if c != "log_weight"]
    return add_columns(docs, make, [("log_weight", T.DoubleType())], text_col=text_col, keep=keep)


def gumbel_key(id_col: str, weight_col: str = "log_weight"):
    """Log weight plus standard Gumbel noise that depends on the id alone."""
    uniform = F.xxhash64(F.lit(5), quoted(id_col)) / F.lit(2.0**64) + 0.5 + 2.0**-54
    return F.round(F.col(weight_col) - F.log(-F.log(uniform * (1 - 2.0**-50))), 6)


def kth_largest(rows: DataFrame, col: str, k: int) -> float | None:
    """The k-th largest value of a column, exactly, by narrowing an interval with counts of 4096 bins a pass."""
    lo, hi, n = rows.agg(F.min(col), F.max(col), F.count(col)).first()
    if k <= 0 or n == 0:
        return None
    if k >= n:
        return lo
    while True:
        step = (hi - lo) / 4096
        inside = rows.where((F.col(col) >= lo) & (F.col(col) <= hi))
        if step <= 0 or lo + step == lo:
            return lo
        bins = inside.groupBy(F.least(F.floor((F.col(col) - lo) / step), F.lit(4095)).alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.min(col).alias("a"), F.max(col).alias("b")).orderBy(F.col("bin").desc()).collect()
        for r in bins:
            if k <= r.n:
                if r.a == r.b:
                    return r.a
                if r.n <= 4096:
                    vals = sorted((x[0] for x in inside.where((F.col(col) >= r.a) & (F.col(col) <= r.b)).select(col).collect()), reverse=True)
                    return vals[k - 1]
                lo, hi = r.a, r.b
                break
            k -= r.n


def resample(docs: DataFrame, model: Model, *, k: int | None = None, id_col: str = "doc_id", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """The columns ``keep`` (default: all) with ``log_weight, sample_key, selected``, which replace input columns of those names.

    ``k`` documents are drawn, by default the model's share of the rows, rounded up. Rows that tie at the last key are
    all selected (keys tie for repeated ids with equal texts). Null and empty texts have weight 1. An empty table
    gives an empty result.
    """
    added = ("log_weight", "sample_key", "selected")
    keep = [c for c in (docs.columns if keep is None else keep) if c not in added]
    scored = cut(score(docs, model, text_col=text_col, keep=list(dict.fromkeys([id_col, *keep]))).withColumn("sample_key", gumbel_key(id_col)), "scored")
    if k is None:
        k = math.ceil(scored.count() * model.share - 1e-9)
    least = kth_largest(scored, "sample_key", k)
    return scored.withColumn("selected", F.lit(False) if least is None else F.col("sample_key") >= least).select(*[quoted(c) for c in keep], *added)
