"""N-best piece segmentation and its inverse.

Text is escaped as SentencePiece does (a space becomes U+2581, one is put in front) and cut where no piece can cross:
before each run of U+2581 that follows another character, and around line feeds. A segment's lattice has all pieces of
the vocabulary as edges; characters without a piece become byte pieces.

A segmentation's score is the sum of its pieces' log probabilities. A unigram model's file has them; the file of a
merge model has merge ranks instead (no probabilities, and their sum says nothing of a segmentation), so there the
probability of a piece is its share under Zipf's law at its rank, 1 / (rank + 10), which is how frequencies fall in a
vocabulary that was merged by frequency. The best segmentation is therefore the most probable one, not the one that
replaying the merges gives. Other scores can be given to ``PieceModel``.

Forward Viterbi scores of all distinct segments of a batch are computed together. They are exact heuristics for a
backward A-star search, which takes hypotheses from the end of a lattice in falling order of (score so far + forward
score at its left end), so the first n that reach the start are the n best. The n best of a whole text change only
among the n - 1 segments with the smallest loss from first to second best, so only their lattices are searched.
"""

from __future__ import annotations

import heapq
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import count, islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import quoted, slices
from .lattice import Vocabulary, by_length

MARK = "▁"
#: Byte pieces score this much below the rarest piece.
BYTE_LOSS = 5.0
_MEMO = 300_000
_SEGMENT = re.compile(rf"\n|{MARK}*[^{MARK}\n]+|{MARK}+")


@dataclass
class PieceModel:
    """``pieces``: number -> string, ``ids``: their ids, ``scores``: their log weights; ``bytes_at``: ids of bytes 0-255."""

    pieces: list[str]
    ids: np.ndarray
    scores: np.ndarray
    bytes_at: list[int]

    def __post_init__(self):
        self.vocabulary = Vocabulary(self.pieces)
        self.byte_score = float(self.scores.min()) - BYTE_LOSS
        self.text_of = {i: chr(b) for b, i in enumerate(self.bytes_at) if b < 0x80} | {int(i): p for i, p in zip(self.ids, self.pieces)}
        self.byte_of = {i: b for b, i in enumerate(self.bytes_at)}


def load(model_path: str) -> PieceModel:
    """Pieces of a SentencePiece model file with byte pieces, and their log probabilities (see above)."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
    size = sp.get_piece_size()
    bytes_at = [sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
    ids = [i for i in range(size) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
    if crossing := [p for i in ids if not _SEGMENT.fullmatch(p := sp.id_to_piece(i))]:
        raise ValueError(f"{len(crossing)} pieces cross a cut between segments, such as {crossing[0]!r}")
    own = np.array([sp.get_score(i) for i in ids])
    if np.logaddexp.reduce(own) > np.log(1.5) or np.logaddexp.reduce(own) < np.log(0.5):  # no distribution: merge ranks
        rank = np.argsort(np.argsort(-own, kind="stable"), kind="stable")
        own = np.log(1.0 / (rank + 10.0)) - np.log((1.0 / (np.arange(len(ids)) + 10.0)).sum())
    return PieceModel([sp.id_to_piece(i) for i in ids], np.array(ids), own, bytes_at)


def escape(text: str) -> str:
    return MARK + text.replace(" ", MARK)


def unescape(text: str) -> str:
    return text.removeprefix(MARK).replace(MARK, " ")


def segments(escaped: str) -> list[str]:
    return _SEGMENT.findall(escaped)


class Segmenter:
    def __init__(self, model: PieceModel):
        self.model = model
        # of known segments: place, ids as little-endian 32-bit words, score, loss to the second best; where the best
        # ids do not read back as the segment, what they read back as
        self.place: dict[str, int] = {}
        self.ids: list[bytes] = []
        self.scores, self.losses = np.zeros(0), np.zeros(0)
        self.odd: dict[int, str] = {}
        self.searched: dict[tuple[str, int], list[tuple[float, bytes]]] = {}  # what A-star has found
        self.number = {p: (float(s), int(i).to_bytes(4, "little")) for p, s, i in zip(model.pieces, model.scores, model.ids)}
        self.longest = model.vocabulary.longest

    def forget(self) -> None:
        self.place.clear(), self.ids.clear(), self.odd.clear(), self.searched.clear()
        self.scores, self.losses = np.zeros(0), np.zeros(0)

    def learn(self, texts: list[list[str]]) -> list[np.ndarray]:
        """Places of the segments of each text; ids, score and loss to the second best of each new one are found."""
        model, place, had = self.model, self.place, len(self.place)
        out = [np.array([place.setdefault(s, len(place)) for s in parts], dtype=np.int64) for parts in texts]
        if len(place) == had:
            return out
        fresh = list(islice(place, had, None))
        self.ids += [b""] * len(fresh)
        scores, losses = np.zeros(len(fresh)), np.zeros(len(fresh))
        for ids, codes in by_length(fresh):
            found = model.vocabulary.match(codes)
            n, length = codes.shape
            own_bytes = 1 + (codes >= 0x80).astype(np.int64) + (codes >= 0x800) + (codes >= 0x10000)
            # hits[size - 1][i]: (rows with a piece of that size at i, its number, its score)
            hits = []
            for size, f in enumerate(found, 1):
                turned = np.ascontiguousarray(f.T)
                if size == 1:
                    score = np.where(turned >= 0, model.scores[turned], own_bytes.T * model.byte_score)
                    hits.append([(slice(None), turned[i], score[i]) for i in range(length)])
                    continue
                at, rows = np.nonzero(turned >= 0)
                number = turned[at, rows]
                score, cuts = model.scores[number], np.searchsorted(at, np.arange(len(turned) + 1))
                hits.append([(rows[x:y], number[x:y], score[x:y]) if y > x else None for x, y in zip(cuts[:-1].tolist(), cuts[1:].tolist())])
            forward, back = np.full((length + 1, n), -np.inf), np.zeros((length + 1, n), dtype=np.int64)
            forward[0] = 0.0
            piece = np.full((length + 1, n), -1, dtype=np.int64)  # the piece that ends at j on the best path, -1: bytes
            for j in range(1, length + 1):
                for size in range(1, min(len(found), j) + 1):
                    if (hit := hits[size - 1][j - size]) is None:
                        continue
                    rows, number, score = hit
                    score = forward[j - size, rows] + score
                    if size == 1:
                        forward[j], back[j], piece[j] = score, 1, number
                        continue
                    better = score > forward[j, rows]
                    rows = rows[better]
                    forward[j, rows], back[j, rows], piece[j, rows] = score[better], size, number[better]
            rest = np.full((length + 1, n), -np.inf)
            rest[length] = 0.0
            on_best = np.zeros((length + 1, n), dtype=bool)
            at, who, used = np.full(n, length), np.arange(n), np.zeros(n, dtype=np.int64)
            packed, plain = np.zeros((n, length), dtype="<u4"), np.ones(n, dtype=bool)
            while len(who):  # ids from the right
                here = at[who]
                on_best[here, who] = True
                p = piece[here, who]
                plain[who[p < 0]] = False
                used[who] += 1
                packed[who, length - used[who]] = model.ids[p]
                at[who] -= back[here, who]
                who = who[at[who] > 0]
            second = np.full(n, -np.inf)
            for i in range(length - 1, -1, -1):
                for size in range(1, min(len(found), length - i) + 1):
                    if (hit := hits[size - 1][i]) is None:
                        continue
                    rows, _, score = hit
                    score = score + rest[i + size, rows]
                    rest[i, rows] = np.maximum(rest[i, rows], score)
                    taken = on_best[i + size, rows] & (back[i + size, rows] == size)  # the best path's own edge
                    second[rows] = np.maximum(second[rows], np.where(taken, -np.inf, forward[i, rows] + score))
            scores[ids], losses[ids] = forward[length], forward[length] - second
            from_, whole = (length - used).tolist(), packed.tobytes()
            for r, k in enumerate(ids.tolist()):
                own = fresh[k]
                if plain[r]:
                    row = whole[4 * (r * length + from_[r]):4 * (r + 1) * length]
                else:  # some character is spelled in bytes
                    path, j = [], length
                    while j > 0:
                        path.append(self.number[own[j - back[j, r]:j]][1] if piece[j, r] >= 0 else self._bytes(own[j - 1]))
                        j -= back[j, r]
                    row = b"".join(reversed(path))
                self.ids[had + k] = row
                if (read := self.read(memoryview(row).cast("I"))) != own:
                    self.odd[had + k] = read
        self.scores, self.losses = np.concatenate([self.scores, scores]), np.concatenate([self.losses, losses])
        return out

    def _bytes(self, char: str) -> bytes:
        return np.array([self.model.bytes_at[x] for x in char.encode("utf-8", "surrogatepass")], dtype="<u4").tobytes()

    def best_of(self, segment: str, n: int) -> list[tuple[float, bytes]]:
        """The n best segmentations of one segment by backward A-star with forward Viterbi scores."""
        length, number = len(segment), self.number
        edges: list[list[tuple[int, float, bytes]]] = [[] for _ in range(length + 1)]
        forward = [0.0] + [-np.inf] * length
        for j in range(1, length + 1):
            own = edges[j]
            for i in range(max(0, j - self.longest), j):
                if piece := number.get(segment[i:j]):
                    own.append((i, *piece))
                elif i == j - 1:
                    raw = self._bytes(segment[i])
                    own.append((i, len(raw) // 4 * self.model.byte_score, raw))
            forward[j] = max(forward[i] + s for i, s, _ in own)
        order, out = count(), []
        heap = [(-forward[length], next(order), length, 0.0, ())]
        while heap and len(out) < n:
            _, _, j, score, tail = heapq.heappop(heap)
            if j == 0:
                out.append((score, b"".join(tail)))
                continue
            for i, s, ids in edges[j]:
                heapq.heappush(heap, (-(forward[i] + score + s), next(order), i, score + s, (ids, *tail)))
        return out

    def combine(self, parts: list[str], at: np.ndarray, n: int) -> tuple[bytes, list[float], list[tuple[int, int, bytes]], str]:
        """Of a text given as segments and their places: the best packed ids, the n best scores (fewer if it has fewer),
        the other segmentations as (start, stop, packed ids that stand there instead), and what the best reads back as."""
        total = float(self.scores[at].sum())
        own = [self.ids[k] for k in at.tolist()]
        back = unescape("".join([self.odd.get(k, p) for k, p in zip(at.tolist(), parts)] if self.odd else parts))
        if n == 1:
            return b"".join(own), [total], [], back
        losses = self.losses[at]
        some = np.argsort(losses, kind="stable")[:n - 1] if len(at) < 4 * n else np.argpartition(losses, n - 2)[:n - 1]
        some = sorted(k for k in some.tolist() if losses[k] < np.inf)
        for k in some:
            if (parts[k], n) not in self.searched:
                self.searched[parts[k], n] = self.best_of(parts[k], n)
        choices = [self.searched[parts[k], n] for k in some]
        cuts = [0, *[k + 1 for k in some]]
        between = [b"".join(own[x:y]) for x, y in zip(cuts, [*some, len(own)])]
        # the best has the first choice everywhere, so what is replaced is the same length as the own ids
        chunks = [between[0], *[x for c, b in zip(choices, between[1:]) for x in (c[0][1], b)]]
        ends = np.cumsum([len(c) // 4 for c in chunks]).tolist()
        # combine: pop the best vector of choices, push those that take one more step in one segment
        start = (0,) * len(some)
        heap, seen, scores, others = [(0.0, start)], {start}, [], []
        while heap and len(scores) < n:
            loss, vector = heapq.heappop(heap)
            scores.append(total - loss)
            if any(vector):
                used = [j for j, y in enumerate(vector) if y]
                lo, hi = 2 * used[0] + 1, 2 * used[-1] + 1  # chunks of the first and the last segment that change
                mine = [choices[(c - 1) // 2][vector[(c - 1) // 2]][1] if c % 2 else chunks[c] for c in range(lo, hi + 1)]
                others.append((ends[lo - 1], ends[hi], b"".join(mine)))
            for j in range(len(some)):
                nxt = (*vector[:j], vector[j] + 1, *vector[j + 1:])
                if nxt[j] < len(choices[j]) and nxt not in seen:
                    seen.add(nxt)
                    heapq.heappush(heap, (sum(c[0][0] - c[y][0] for c, y in zip(choices, nxt)), nxt))
        return b"".join(chunks), scores, others, back

    def encode(self, text: str, n: int = 1) -> list[tuple[float, list[int]]]:
        """The n best (score, ids) of a text, best first; fewer if it has fewer."""
        parts = segments(escape(text))
        packed, scores, others, _ = self.combine(parts, self.learn([parts])[0], n)
        best = np.frombuffer(packed, dtype="<u4").tolist()
        return list(zip(scores, [best, *[best[:a] + np.frombuffer(x, dtype="<u4").tolist() + best[b:] for a, b, x in others]]))

    def decode(self, ids: list[int]) -> str:
        """The text that ids stand for."""
        return unescape(self.read(ids))

    def read(self, ids: list[int]) -> str:
        """The escaped text that ids stand for."""
        text_of = self.model.text_of
        try:
            return "".join([text_of[i] for i in ids])
        except KeyError:  # bytes of longer characters
            pass
        out, raw = [], bytearray()
        for i in ids:
            if i in self.model.byte_of:
                raw.append(self.model.byte_of[i])
                continue
            if raw:
                out.append(raw.decode("utf-8", "surrogatepass"))
                raw.clear()
            out.append(self.model.text_of[i])
        if raw:
            out.append(raw.decode("utf-8", "surrogatepass"))
        return "".join(out)


SCHEMA = "id {id}, n_pieces long, ids array<int>, ids_crc32 long, score double, nbest_scores array<double>, others array<struct<start: int, stop: int, ids: array<int>>>, decoded string, round_trip boolean"


def _lists(rows: list[bytes]) -> pa.Array:
    """Lists of 32-bit ids from their bytes."""
    ends = np.cumsum([0, *[len(r) // 4 for r in rows]], dtype=np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(rows), dtype="<i4")))


def segment_documents(docs: DataFrame, model_path: str, *, n: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The best segmentation (ids, their number and checksum, score), the scores of the n best, the others, the decoded text.

    Each of ``others``, second best first, is what stands in the best one's ids from ``start`` up to ``stop`` instead.
    Null text counts as empty (the front mark alone). U+2581 in a text reads back as a space, and ``round_trip`` says
    so. Texts are read whole; equal texts get equal values (segmentations of one score in any order); an empty table
    gives an empty result. Other columns are ignored.
    """
    names = ["id", "n_pieces", "ids", "ids_crc32", "score", "nbest_scores", "others", "decoded", "round_trip"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Segmenter(load(model_path))
        for b in (part for whole in batches for part in slices(whole, 1, size=1 << 22)):
            texts = [t or "" for t in b.column(1).to_pylist()]
            if len(own.place) > _MEMO:
                own.forget()
            parts = [segments(escape(t)) for t in texts]
            best, scores, others, backs = map(list, zip(*[own.combine(p, at, n) for p, at in zip(parts, own.learn(parts))]))
            flat = [x for o in others for x in o]
            ends = pa.array(np.cumsum([0, *map(len, others)], dtype=np.int32))
            edits = pa.StructArray.from_arrays([pa.array([x[0] for x in flat], pa.int32()), pa.array([x[1] for x in flat], pa.int32()), _lists([x[2] for x in flat])], names=["start", "stop", "ids"])
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(0), pa.array([len(x) // 4 for x in best], pa.int64()), _lists(best), pa.array([zlib.crc32(x) for x in best], pa.int64()),
                    pa.array([round(s[0], 4) for s in scores], pa.float64()), pa.array([[round(x, 4) for x in s] for s in scores], pa.list_(pa.float64())),
                    pa.ListArray.from_arrays(ends, edits), pa.array(backs, pa.string()), pa.array([x == t for x, t in zip(backs, texts)], pa.bool_()),
                ],
                names=names,
            )

    return docs.select(quoted(id_col).alias("id"), quoted(text_col).alias("text")).mapInArrow(run, SCHEMA.format(id=dict(docs.dtypes)[id_col]))
