"""URL filters over a sorted digest array.

Entries (``host`` + path prefix) become 64-bit xxhash keys in one sorted array beside an offset array and the stored
strings. Workers memory-map the array, probe it with a vectorised binary search and confirm every hit against the
stored string, so a digest collision never judges a URL. A URL is probed under each of its host's suffixes and each
path prefix whose length occurs in the list; the longest entry decides.
"""

from __future__ import annotations

import os
import re
import tempfile
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import UPPER, quoted, slices

SEED = 0
#: Largest array that is sent to the workers whole; longer lists go through ``judge_urls_by_join``.
MAX_BYTES = 256 << 20
#: Hosts that ``hosts_named`` gathers at most; more need ``judge_urls_by_join``.
MAX_HOSTS = 4_000_000
_MAGIC = b"DIGARR01"


def split_url(url: str | None) -> tuple[str, str]:
    """Host (A-Z lower-cased) and path; both empty for a null or one without ``://``."""
    if url is None:
        return "", ""
    _, mark, rest = url.partition("://")
    if not mark:
        return "", ""
    host = re.match(r"[^/?#]*", rest).group()
    path = re.match(r"[^?#]*", rest[len(host):]).group()
    return re.sub(r"[A-Z]+", lambda m: m.group().lower(), host), path


class DigestArray:
    """Sorted 64-bit digests with the strings and an 8-bit verdict each; ``pack`` to bytes, ``map`` from a file."""

    def __init__(self, keys, verdicts, offsets, blob):
        self.keys, self.verdicts, self.offsets, self.blob = keys, verdicts, offsets, blob

    @classmethod
    def build(cls, entries: Iterable[tuple[str, int]], digest=None) -> DigestArray:
        digest = digest or (lambda b: xxhash.xxh64_intdigest(b, SEED))
        rows = sorted({(digest(s.encode()), s.encode(), int(v)) for s, v in entries})
        strings = [s for _, s, _ in rows]
        offsets = np.zeros(len(rows) + 1, dtype="<i8")
        np.cumsum([len(s) for s in strings], out=offsets[1:])
        return cls(np.array([k for k, _, _ in rows], dtype="<u8"), np.array([v for *_, v in rows], dtype="u1"), offsets, np.frombuffer(b"".join(strings), dtype="u1"))

    def pack(self) -> bytes:
        head = np.array([len(self.keys), len(self.blob)], dtype="<i8").tobytes()
        return _MAGIC + head + self.keys.tobytes() + self.offsets.tobytes() + self.verdicts.tobytes() + self.blob.tobytes()

    @classmethod
    def map(cls, path: str) -> DigestArray:
        raw = np.memmap(path, dtype="u1", mode="r")
        if bytes(raw[:8]) != _MAGIC:
            raise ValueError(f"{path} holds no digest array")
        n, blob = (int(x) for x in raw[8:24].view("<i8"))
        a, b, c = 24, 24 + 8 * n, 24 + 8 * n + 8 * (n + 1)
        return cls(raw[a:b].view("<u8"), raw[c:c + n], raw[b:c].view("<i8"), raw[c + n:c + n + blob])

    def find(self, digests: np.ndarray, strings: list[bytes]) -> np.ndarray:
        """Index of the entry that equals each string, or -1."""
        at = np.searchsorted(self.keys, digests)
        out = np.full(len(digests), -1, dtype=np.int64)
        live = np.flatnonzero(at < len(self.keys))
        live = live[self.keys[at[live]] == digests[live]]
        for i in live:  # digest hits only: confirm against the stored string, walk over equal digests
            k = int(at[i])
            while k < len(self.keys) and self.keys[k] == digests[i]:
                if bytes(self.blob[self.offsets[k]:self.offsets[k + 1]]) == strings[i]:
                    out[i] = k
                    break
                k += 1
        return out


def map_bytes(packed: bytes) -> DigestArray:
    """Put a shipped array into an unlinked file of this worker and memory-map it."""
    fd, path = tempfile.mkstemp(suffix=".digests")
    with os.fdopen(fd, "wb") as f:
        f.write(packed)
    array = DigestArray.map(path)
    os.unlink(path)
    return array


@dataclass(frozen=True)
class UrlRules:
    """``rules``: (entry, verdict) in order; an entry is host plus path prefix, and may be a bare host."""

    rules: tuple[tuple[str, str], ...]

    @property
    def verdicts(self) -> list[str]:
        return sorted({v for _, v in self.rules})

    def lengths(self) -> list[int]:
        """Path-prefix lengths that occur."""
        return sorted({len(s) - len(_host_of(s)) for s, _ in self.rules}, reverse=True)

    def array(self, digest=None) -> DigestArray:
        names = self.verdicts
        return DigestArray.build([(s, names.index(v)) for s, v in self.rules], digest)


def _host_of(entry: str) -> str:
    return entry.split("/", 1)[0]


def _candidates(host: str, path: str, lengths: list[int]) -> list[str]:
    """Every entry that would fit, whole host first, longest path first; the longest string wins."""
    suffixes, at = [host] if host else [], 0
    while (at := host.find(".", at) + 1) > 0:
        suffixes.append(host[at:])
    found = [s + path[:n] for s in suffixes for n in lengths if n <= len(path)]
    return sorted(set(found), key=lambda s: -len(s))


def judge(urls: list[str | None], array: DigestArray, lengths: list[int], digest=None):
    """Host, path and the index of the deciding entry (-1: none) of each URL; one binary search for the batch."""
    digest = digest or (lambda b: xxhash.xxh64_intdigest(b, SEED))
    parts = [split_url(u) for u in urls]
    seen: dict[tuple[str, str], list[str]] = {}
    flat: dict[str, int] = {}
    most = max(lengths, default=0)
    for h, p in parts:
        key = (h, p[:most])
        if key not in seen:
            seen[key] = _candidates(h, p, lengths)
            for s in seen[key]:
                flat.setdefault(s, len(flat))
    strings = [s.encode() for s in flat]
    hits = array.find(np.array([digest(s) for s in strings], dtype="<u8"), strings) if strings else np.zeros(0, dtype=np.int64)
    won = {key: next((int(hits[flat[s]]) for s in found if hits[flat[s]] >= 0), -1) for key, found in seen.items()}
    return parts, [won[(h, p[:most])] for h, p in parts]


def filter_urls(pages: DataFrame, rules: UrlRules, blocklist: Iterable[str] = (), *, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """``id, host, path, rule, verdict`` of every URL.

    ``rules`` overrule ``blocklist`` (entries of hosts with or without a path, for the host and its subdomains); a URL
    that neither names gets ``default``. Null URLs and URLs without ``://`` have empty host and path and match
    nothing. Repeated rows are judged alike; an empty table gives an empty result; other columns are ignored.
    """
    spark = pages.sparkSession
    listed = UrlRules(tuple((s, "block") for s in blocklist))
    packed = [(r.array().pack(), r.lengths(), r.verdicts) for r in (rules, listed)]
    if (size := sum(len(p) for p, *_ in packed)) > MAX_BYTES:
        raise ValueError(f"digest arrays of {size} bytes exceed {MAX_BYTES}; use judge_urls_by_join")
    shipped = spark.sparkContext.broadcast(packed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (own, own_len, own_names), (block, block_len, _) = [(map_bytes(p), n, v) for p, n, v in shipped.value]
        for b in (part for whole in batches for part in slices(whole, 1, 8192)):
            urls = b.column(1).to_pylist()
            parts, at = judge(urls, own, own_len)
            _, listed_at = judge(urls, block, block_len)
            texts = {k: bytes(own.blob[own.offsets[k]:own.offsets[k + 1]]).decode() for k in set(at) if k >= 0}
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(0),
                    pa.array([h for h, _ in parts], pa.string()),
                    pa.array([p for _, p in parts], pa.string()),
                    pa.array([texts.get(k) for k in at], pa.string()),
                    pa.array([own_names[own.verdicts[k]] if k >= 0 else "block" if j >= 0 else default for k, j in zip(at, listed_at)], pa.string()),
                ],
                names=["id", "host", "path", "rule", "verdict"],
            )

    kind = dict(pages.dtypes)[id_col]
    return pages.select(quoted(id_col).alias("id"), quoted(url_col).alias("url")).mapInArrow(run, f"id {kind}, host string, path string, rule string, verdict string")


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host and path as columns, as ``split_url`` gives them."""
    rest = F.when(F.instr(url, "://") > 0, F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)).otherwise(F.lit(""))
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), UPPER, UPPER.lower())
    return F.coalesce(host, F.lit("")), F.coalesce(F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def hosts_named(pages: DataFrame, words: Iterable[str], *, url_col: str = "url") -> list[str]:
    """A blocklist from the pages themselves: their hosts that have one of ``words`` as a part between dots and hyphens.

    Null URLs and URLs without ``://`` have no host; repeated rows count once; other columns are ignored; an empty
    table gives an empty list. Over MAX_HOSTS hosts are refused.
    """
    host = url_parts(quoted(url_col))[0]
    own = pages.select(host.alias("host")).where(F.arrays_overlap(F.split("host", "[.-]"), F.array(*[F.lit(w) for w in words]))).distinct()
    found = own.limit(MAX_HOSTS + 1).collect()
    if len(found) > MAX_HOSTS:
        raise ValueError(f"more than {MAX_HOSTS} hosts; use judge_urls_by_join")
    return sorted(r.host for r in found)


def judge_urls_by_join(pages: DataFrame, entries: DataFrame, *, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """For lists too long to ship: ``entries(entry string)`` stays distributed.

    Host suffixes and path prefixes up to each ``/`` are exploded as candidates (bounded by a URL's own length) and
    joined on the 64-bit digest and the string. Gives ``id, entry`` of the longest matching entry (null: none). Path
    prefixes of entries must end at a ``/`` or be empty. Null URLs and URLs without ``://`` match nothing, repeated rows
    are judged alike, ties in length cannot be; other columns are ignored; an empty table gives an empty result.
    """
    host, path = url_parts(quoted(url_col))
    labels, steps = F.split("host", r"\."), F.split("path", "/")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    prefixes = F.array_union(F.array(F.lit("")), F.when(F.size(steps) > 1, F.transform(F.sequence(F.lit(1), F.size(steps) - 1), lambda i: F.concat(F.array_join(F.slice(steps, 1, i), "/"), F.lit("/")))).otherwise(F.array().cast("array<string>")))
    asked = pages.select(F.monotonically_increasing_id().alias("_row"), quoted(id_col).alias("id"), host.alias("host"), path.alias("path")).select("_row", "id", F.explode(suffixes).alias("s"), prefixes.alias("ps")).select("_row", "id", F.explode(F.transform("ps", lambda p: F.concat("s", p))).alias("entry"))
    asked = asked.withColumn("d", F.xxhash64("entry"))
    listed = entries.select("entry").distinct().withColumn("d", F.xxhash64("entry")).withColumn("hit", F.lit(True))
    best = asked.join(listed, ["d", "entry"], "left").groupBy("_row", "id").agg(F.max(F.when(F.col("hit"), F.struct(F.length("entry").alias("n"), "entry"))).alias("m"))
    return best.select("id", F.col("m.entry").alias("entry"))
