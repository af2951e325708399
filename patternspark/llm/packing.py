"""Sequence packing by vector best-fit.

Documents become token pieces of at most one sequence; only longer ones are cut, and only their first piece may be
short. A piece asks for tokens, one document slot and attention cost (its squared length, as attention stays inside a
piece). Pieces are dealt into buckets of bounded size by hash, each bucket is packed in falling order of length: of
the open sequences that can take the piece under every capacity, the one with the best weighted dot-product or the
smallest weighted residual norm gets it.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, quoted, slices

BUCKET = 16384
PIECES = "id {id}, piece int, start long, length long, ids_crc32 long"


@dataclass(frozen=True)
class Capacity:
    """What a sequence holds: tokens, documents and attention cost (a piece's length squared).

    At the defaults documents bind for sequences of very short ones; 1024 tokens in one piece take all the attention.
    Weights are those of the three in the choice among the sequences that fit.
    """

    tokens: int = 1024
    documents: int = 64
    attention: int = 1024**2
    rule: str = "norm"
    weights: tuple[float, float, float] = (1.0, 1.0, 1.0)


#: Characters on which both tokenizer libraries split alike; other texts go to the slower library, whose ids count.
_PLAIN = re.compile(r"[\t\n\r -~¡-ɏ‐-‧‰-⁞€]*")


class Encoder:
    """Ids of ``tokenizers`` for a byte-level BPE file, from ``tiktoken`` (about eight times faster) where both agree."""

    def __init__(self, tokenizer_path: str, ranks_path: str | None = None, pattern: str | None = None):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.exact = Tokenizer.from_file(tokenizer_path)
        self.fast, self.special = None, []
        if ranks_path:
            import base64

            import tiktoken

            with open(ranks_path, "rb") as f:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            self.fast = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
            self.special = [t.content for t in self.exact.get_added_tokens_decoder().values()]

    def ids(self, text: str) -> np.ndarray:
        if self.fast is not None and _PLAIN.fullmatch(text) and not any(s in text for s in self.special):
            return self.fast.encode_to_numpy(text, disallowed_special=()).astype("<u4")
        return np.array(self.exact.encode(text, add_special_tokens=False).ids, dtype="<u4")


def token_pieces(docs: DataFrame, tokenizer_path: str, *, ranks_path: str | None = None, pattern: str | None = None, end_id: int = 2, width: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, piece, start, length, ids_crc32`` of every document's pieces.

    Null text counts as empty (one end token). Texts are read whole, whatever their length; repeated rows give repeated
    pieces; other columns are ignored; an empty table gives an empty result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = Encoder(tokenizer_path, ranks_path, pattern)
        end = np.array([end_id], dtype="<u4")
        for b in (part for whole in batches for part in slices(whole, 1)):
            row, piece, start, length, crc = [], [], [], [], []
            for i, text in enumerate(b.column(1).to_pylist()):
                ids = np.concatenate([enc.ids(text or ""), end])
                first = len(ids) % width or width
                for k, at in enumerate([0, *range(first, len(ids), width)]):
                    part = ids[at:first if k == 0 else at + width]
                    row.append(i), piece.append(k), start.append(at), length.append(len(part)), crc.append(zlib.crc32(part.tobytes()))
            yield pa.RecordBatch.from_arrays(
                [b.column(0).take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc))],
                names=["id", "piece", "start", "length", "ids_crc32"],
            )

    return docs.select(quoted(id_col).alias("id"), quoted(text_col).alias("text")).mapInArrow(run, PIECES.format(id=dict(docs.dtypes)[id_col]))


def best_fit(lengths: np.ndarray, cap: Capacity) -> tuple[np.ndarray, np.ndarray]:
    """Sequence number and offset of each piece; ``lengths`` must fall. Every capacity holds in every sequence."""
    full = np.array([cap.tokens, cap.documents, cap.attention], dtype=np.float64)
    weights = np.asarray(cap.weights, dtype=np.float64)
    n = len(lengths)
    seq, offset = np.zeros(n, dtype=np.int64), np.zeros(n, dtype=np.int64)
    free, name = np.empty((3, n)), np.zeros(n, dtype=np.int64)  # of the open sequences: what is left, their numbers
    opened = alive = 0
    least = int(lengths[-1]) if n else 0
    for i, size in enumerate(lengths.tolist()):
        need = np.array([size, 1.0, float(size) * size])
        if (need > full).any():
            raise ValueError(f"a piece of {size} tokens exceeds the capacity")
        left = free[:, :alive]
        fits = np.flatnonzero((left[0] >= need[0]) & (left[1] >= need[1]) & (left[2] >= need[2]))
        if len(fits):
            room = left[:, fits]
            if cap.rule == "dot":
                k = int(fits[np.argmax(((weights * need / full**2)[:, None] * room).sum(0))])
            else:
                k = int(fits[np.argmin((weights[:, None] * ((room - need[:, None]) / full[:, None]) ** 2).sum(0))])
        else:
            k = alive
            free[:, k], name[k] = full, opened
            alive, opened = alive + 1, opened + 1
        seq[i], offset[i] = name[k], cap.tokens - int(free[0, k])
        free[:, k] -= need
        if free[0, k] < least or free[1, k] < 1 or free[2, k] < float(least) * least:  # nothing fits any more: close it
            alive -= 1
            free[:, k], name[k] = free[:, alive], name[alive]
    return seq, offset


def pack(pieces: DataFrame, cap: Capacity = Capacity(), *, bucket: int = BUCKET) -> DataFrame:
    """Add ``sequence_id`` and ``offset`` to pieces.

    A bucket holds about ``bucket`` pieces, so a task's memory does not grow with the table. Whole-sequence pieces
    take part too. Ties in length go by id and piece, so a result does not depend on the order of rows; copies of a
    row (same id and piece) are packed each for itself. An empty table gives an empty result.
    """
    pieces = cut(pieces, "pieces")
    whole = pieces.where(F.col("length") >= cap.tokens).withColumn("sequence_id", -F.monotonically_increasing_id() - 1).withColumn("offset", F.lit(0).cast("long"))
    rest = pieces.where(F.col("length") < cap.tokens)
    buckets = max(1, round(rest.count() / bucket))
    names = ["id", "piece", "start", "length", "ids_crc32"]

    def run(key, group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["length", "id", "piece"], ascending=[False, True, True], kind="stable", ignore_index=True)
        seq, offset = best_fit(group["length"].to_numpy(), cap)
        return group[names].assign(sequence_id=(int(key[0]) << 40) + seq, offset=offset)

    kind = dict(pieces.dtypes)["id"]
    packed = rest.withColumn("b", F.pmod(F.xxhash64("id", "piece", "start"), F.lit(buckets))).groupBy("b").applyInPandas(run, PIECES.format(id=kind) + ", sequence_id long, offset long")
    return packed.unionByName(whole)
