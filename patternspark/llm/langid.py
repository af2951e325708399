"""Language identification by unigrams that are marginalised over segmentations.

Each language has a probability for every piece of a fixed public vocabulary. A word's probability is the sum over all
its segmentations of the product of their pieces' probabilities (forward algorithm); a text's is the product over its
words. Piece probabilities are fitted by expectation maximisation over the segmentations of a bounded sample.

Words are runs of letters, lower-cased, with a start mark, whole whatever their length: forward and backward sums are
rescaled as they grow. A batch's distinct words are scored together, words of one length as one matrix, so cost grows
with the distinct words and not with Python calls per word.
"""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import add_columns, cut, quoted, slices
from .lattice import Vocabulary, by_length

UND = "und"
#: Documents per language that a model is fitted on, about; every language has as many or all it has.
SAMPLE = 400
ROUNDS = 2
SMOOTH = 0.1
FLOOR = 1e-7
#: Sums are rescaled after so many letters: they stay in range as long as FLOOR to this power does.
STEP = 16
_LETTERS = re.compile(r"[^\W\d_]+")
_MEMO = 200_000


def public_pieces(model_path: str) -> list[str]:
    """The normal pieces of a SentencePiece model file (no control, unknown or byte pieces)."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
    return [sp.id_to_piece(i) for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]


def words(text: str) -> list[str]:
    found = _LETTERS.findall(text.lower())
    return found if all(map(str.isascii, found)) else [w for w in found if any(map(str.isalpha, w))]


@dataclass
class Model:
    """``table``: (pieces + 1, languages) probabilities; the last row is the floor of an unlisted character."""

    vocabulary: Vocabulary
    languages: list[str]
    table: np.ndarray

    def _edges(self, codes: np.ndarray) -> list[list[tuple[np.ndarray, np.ndarray] | None]]:
        """``[size - 1][i]``: rows with a piece of that size at i and its number."""
        found = self.vocabulary.match(codes)
        found[0] = np.where(found[0] < 0, len(self.table) - 1, found[0])  # any character may stand alone
        out = []
        for f in found:
            turned = np.ascontiguousarray(f.T)
            at, rows = np.nonzero(turned >= 0)
            piece, cuts = turned[at, rows], np.searchsorted(at, np.arange(len(turned) + 1))
            out.append([(rows[x:y], piece[x:y]) if y > x else None for x, y in zip(cuts[:-1].tolist(), cuts[1:].tolist())])
        return out

    def _forward(self, edges: list, n: int, length: int) -> tuple[np.ndarray, np.ndarray]:
        """Sums over the segmentations of each start: (length + 1, n, languages), and the logs of what they were divided by."""
        alpha, log = np.zeros((length + 1, n, len(self.languages))), np.zeros((length + 1, n, len(self.languages)))
        alpha[0] = 1.0
        for j in range(1, length + 1):
            log[j] = log[j - 1]
            for size in range(1, min(len(edges), j) + 1):
                if hit := edges[size - 1][j - size]:
                    rows, piece = hit
                    share = alpha[j - size, rows] * self.table[piece]
                    if j - size < j // STEP * STEP - 1:  # from before the last rescaling
                        share *= np.exp(log[j - size, rows] - log[j, rows])
                    alpha[j, rows] += share
            if j % STEP == STEP - 1:
                log[j] += np.log(alpha[j])
                alpha[j] = 1.0
        return alpha, log

    def log_words(self, strings: list[str]) -> np.ndarray:
        """(words, languages) log probabilities."""
        out = np.zeros((len(strings), len(self.languages)))
        for ids, codes in by_length(["▁" + s for s in strings]):
            alpha, log = self._forward(self._edges(codes), *codes.shape)
            out[ids] = np.log(alpha[-1]) + log[-1]
        return out

    def expected(self, strings: list[str], weights: np.ndarray, language: int) -> np.ndarray:
        """Expected piece counts of one language's weighted words."""
        total = np.zeros(len(self.table))
        one = Model(self.vocabulary, [self.languages[language]], self.table[:, [language]])
        for ids, codes in by_length(["▁" + s for s in strings]):
            n, length = codes.shape
            edges = one._edges(codes)
            alpha, front = (x[:, :, 0] for x in one._forward(edges, n, length))
            whole = np.log(alpha[-1]) + front[-1]
            beta, back = np.zeros((length + 1, n)), np.zeros((length + 1, n))
            beta[length] = 1.0
            for i in range(length - 1, -1, -1):
                back[i] = back[i + 1]
                for size in range(1, min(len(edges), length - i) + 1):
                    if hit := edges[size - 1][i]:
                        rows, piece = hit
                        share = one.table[piece, 0] * beta[i + size, rows]
                        total += np.bincount(piece, alpha[i, rows] * share * np.exp(front[i, rows] + back[i + size, rows] - whole[rows]) * weights[ids[rows]], minlength=len(total))
                        beta[i, rows] += share * np.exp(back[i + size, rows] - back[i, rows])
                if i % STEP == 0:
                    back[i] += np.log(beta[i])
                    beta[i] = 1.0
        return total


def fit(docs: DataFrame, pieces: list[str], *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", train=None, sample: int = SAMPLE, rounds: int = ROUNDS) -> Model:
    """Fit on rows with a language for which ``train`` holds, about ``sample`` documents per language.

    Which documents are taken depends on their id's hash alone. A language that no text with letters has is not
    learned. Without training rows the model has no language and every prediction is ``und``.
    """
    vocabulary = Vocabulary(pieces)
    known = docs.where(quoted(lang_col).isNotNull() & quoted(text_col).isNotNull())
    known = known.where(train) if train is not None else known
    known = known.select(quoted(id_col).alias("id"), quoted(lang_col).alias("lang"), quoted(text_col).alias("text"))
    # One row per language: what is gathered does not grow with the table.
    share = {r[0]: min(1.0, sample / r[1]) for r in known.groupBy("lang").count().collect()}
    if not share:
        return Model(vocabulary, [], np.full((len(pieces) + 1, 0), FLOOR))
    uniform = (F.xxhash64(F.lit(11), F.col("id")) / F.lit(2.0**64)) + 0.5
    limit = F.create_map(*[x for k, v in share.items() for x in (F.lit(k), F.lit(v))])[F.col("lang")]
    picked = known.where(uniform <= limit).select("lang", "text")

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (part for whole in batches for part in slices(whole, 1)):
            counts: Counter = Counter()
            for lang, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                counts.update((lang, w) for w in words(text))
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in counts], pa.string()), pa.array([k[1] for k in counts], pa.string()), pa.array(list(counts.values()), pa.int64())], names=["lang", "word", "n"])

    counted = cut(picked.mapInArrow(split, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n")), "words")
    languages = sorted(r[0] for r in counted.select("lang").distinct().collect())
    table = np.full((len(pieces) + 1, len(languages)), 1.0 / (len(pieces) + 1))
    for _ in range(rounds):
        now = docs.sparkSession.sparkContext.broadcast(Model(vocabulary, languages, table))

        def step(batches: Iterator[pa.RecordBatch], now=now) -> Iterator[pa.RecordBatch]:
            model = now.value
            place = {x: i for i, x in enumerate(model.languages)}
            total: dict[int, np.ndarray] = {}
            for b in batches:
                own = defaultdict(lambda: ([], []))
                for lang, w, n in zip(*(b.column(i).to_pylist() for i in range(3))):
                    own[place[lang]][0].append(w)
                    own[place[lang]][1].append(n)
                for lang, (ws, ns) in own.items():
                    total[lang] = total.get(lang, 0) + model.expected(ws, np.array(ns, dtype=np.float64), lang)
            for lang, c in total.items():
                at = np.flatnonzero(c)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), lang, dtype=np.int32)), pa.array(at.astype(np.int32)), pa.array(c[at])], names=["l", "p", "c"])

        # At most languages x pieces rows, whatever the table's size.
        got = counted.mapInArrow(step, "l int, p int, c double").groupBy("l", "p").agg(F.sum("c").alias("c")).toPandas()
        counts = np.zeros_like(table)
        counts[got["p"], got["l"]] = got["c"]
        counts[-1] = 0
        table = np.maximum((counts + SMOOTH) / (counts + SMOOTH).sum(0), FLOOR)
        table[-1] = FLOOR
        now.unpersist()
    return Model(vocabulary, languages, table)


class Scorer:
    """Scores texts of many batches; keeps the log probabilities of a bounded number of words."""

    def __init__(self, model: Model):
        self.model, self.place, self.rows = model, {}, np.zeros((0, len(model.languages)))

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        langs, scores = [], []
        lo = 0
        while lo < len(texts):  # at most about 4 MB of text at a time
            hi, held = lo, 0
            while hi < len(texts) and (hi == lo or held < 1 << 22):
                held += len(texts[hi] or "")
                hi += 1
            found = [words(t) if t else [] for t in texts[lo:hi]]
            if len(self.place) > _MEMO:
                self.place, self.rows = {}, self.rows[:0]
            place, had = self.place, len(self.place)
            at = [[place.setdefault(w, len(place)) for w in ws] for ws in found]
            if len(place) > had:
                fresh = list(place)[had:]
                self.rows = np.concatenate([self.rows, self.model.log_words(fresh)])
            for ids in at:
                if not ids or not self.model.languages:
                    langs.append(UND)
                    scores.append(0.0)
                    continue
                total = self.rows[np.array(ids)].sum(0)
                best = int(np.argmax(total))
                langs.append(self.model.languages[best])
                scores.append(round(float(1.0 / np.exp(total - total[best]).sum()), 6))
            lo = hi
        return langs, scores


def predict(docs: DataFrame, model: Model, *, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """The columns ``keep`` (default: all) and ``lang_pred``, ``score`` (the language's posterior under equal priors).

    Null texts and texts without a letter give ``und`` and 0. Ties go to the first language by name. Texts are read
    whole. Input columns called ``lang_pred`` or ``score`` are replaced. An empty table gives an empty result.
    """
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        scorer = Scorer(shipped.value)

        def work(texts: list[str | None]) -> list[pa.Array]:
            langs, scores = scorer.predict(texts)
            return [pa.array(langs, pa.string()), pa.array(scores, pa.float64())]

        return work

    keep = [c for c in (docs.columns if keep is None else keep) if c not in ("lang_pred", "score")]
    return add_columns(docs, make, [("lang_pred", T.StringType()), ("score", T.DoubleType())], text_col=text_col, keep=keep)
