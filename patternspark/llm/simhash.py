"""Near-duplicate groups by SimHash fingerprints and pigeonhole blocks.

Fingerprints are cut into k blocks; two that differ in at most d bits agree on at least k - d blocks, so they share a
key in one of C(k, d) tables. Equal fingerprints are merged first, so copies never meet each other. A table's key with
few fingerprints is compared inside one record; the record gives a spanning tree of each linked part, not its pairs.
A key with more fingerprints than ``most`` takes an exact linear way instead: two fingerprints differ in at most d
bits just when flipping at most d/2 bits of one (rounded down) and d/2 of the other (rounded up) can give the same
word, so each fingerprint is listed under every word that near (2081 for d = 4) and those that share a word are linked
in a star.

Near copies by the similarity of their shingles go the same way first: what fingerprints and blocks link is held against
the exact similarity. Similar pairs whose fingerprints are further apart follow exactly: the prefixes of ordered shingle
sets meet in a key for every pair that is similar enough, at every size of the table.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import ceil, comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import ascii_lower_py, cut, quoted, scratch, slices
from .graph import components

BITS = 64
SEED = 42
#: A fingerprint is hot from N / HOT_SHARE rows on, so there are at most HOT_SHARE hot ones to broadcast.
HOT_SHARE, HOT_LEAST = 2048, 256
#: Ids that are held against all documents are broadcast up to this many, and joined by shuffle beyond.
BROADCAST_IDS = 500_000


def words(text: str) -> list[bytes]:
    """Runs of characters other than space and U+0009 to U+000D, A-Z lower-cased, in UTF-8."""
    return ascii_lower_py(text).encode("utf-8", "surrogatepass").split()


def shingle_hashes(text: str | None, size: int) -> np.ndarray:
    """Hashes of a text's shingles in their order, repeats included; of a shorter text: one of all its words."""
    ws = words(text or "")
    if not ws:
        return np.zeros(0, dtype="<u8")
    joined = b" ".join(ws)
    ends = np.cumsum([len(w) + 1 for w in ws]) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])[:max(1, len(ws) - size + 1)]
    digest = xxhash.xxh64_intdigest
    return np.array([digest(joined[a:b], SEED) for a, b in zip(starts.tolist(), ends[min(size, len(ws)) - 1:].tolist())], dtype="<u8")


def majority(h: np.ndarray) -> int:
    """A bit is 1 if it is set in over half of the hashes; 0 if there are none."""
    ones = np.zeros(BITS, dtype=np.int64)
    for at in range(0, len(h), 65536):
        ones += np.unpackbits(h[at:at + 65536].view("u1").reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(h), bitorder="little").view("<u8")[0])


def fingerprint(text: str | None, size: int = 4) -> int:
    """The majority of the shingles' hashes; 0 for a text without words."""
    return majority(shingle_hashes(text, size))


def fingerprints(docs: DataFrame, *, size: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, fp`` (64 bits as a signed long) of every row."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _small(batches):
            fps = np.array([fingerprint(t, size) for t in b.column(1).to_pylist()], dtype="<u8")
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view("<i8"), pa.int64())], names=["id", "fp"])

    return docs.select(quoted(id_col).alias("id"), quoted(text_col).alias("text")).mapInArrow(run, f"id {dict(docs.dtypes)[id_col]}, fp long")


def block_masks(k: int, distance: int) -> list[int]:
    """Masks of the C(k, distance) tables: each keeps k - distance of k blocks of nearly equal width."""
    edges = [BITS * i // k for i in range(k + 1)]
    blocks = [sum(1 << b for b in range(edges[i], edges[i + 1])) for i in range(k)]
    return [sum(blocks[i] for i in keep) for keep in combinations(range(k), k - distance)]


def blocks_for(n: int, distance: int, per_row: float = 4.0) -> int:
    """Fewest blocks for which chance partners of a fingerprint stay under ``per_row`` over all tables."""
    k = distance + 1
    while k < BITS and comb(k, distance) * n / 2.0 ** ((k - distance) * (BITS // k)) > per_row and comb(k, distance) < 1000:
        k += 1
    return k


def _linked(fps: np.ndarray, distance: int) -> list[tuple[int, int]]:
    """A spanning tree (each edge a link of at most ``distance`` bits) of each part that such links make of ``fps``.

    A tree starts at the fingerprint nearest to the bitwise majority, so copies of one text hang on it directly.
    """
    if len(fps) == 2:
        a, b = int(fps[0]), int(fps[1])
        return [(a, b)] if ((a ^ b) & (2**64 - 1)).bit_count() <= distance else []
    fps = np.sort(fps)
    ones = np.unpackbits(fps.view("u1").reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    middle = np.packbits(2 * ones > len(fps), bitorder="little").view("<i8")
    rest = fps[np.argsort(np.bitwise_count((fps ^ middle).view("<u8")), kind="stable")]
    out = []
    while len(rest) > 1:
        todo, rest = [rest[0]], rest[1:]
        for node in todo:
            if not len(rest):
                break
            near = np.bitwise_count((rest ^ node).view("<u8")) <= distance
            if near.any():
                found, rest = rest[near], rest[~near]
                out += [(int(node), x) for x in found.tolist()]
                todo.extend(found)
    return out


def near_words(distance: int) -> np.ndarray:
    """Words of at most distance / 2 set bits."""
    out = [0]
    for w in range(1, distance // 2 + 1):
        out += [sum(1 << b for b in c) for c in combinations(range(BITS), w)]
    return np.array(out, dtype="<u8").view("<i8")


def fingerprint_links(fps: DataFrame, *, distance: int = 4, blocks: int | None = None, most: int = 2048, within: str | None = None) -> DataFrame:
    """Links ``a, b`` between distinct fingerprints ``fp`` that connect just those within ``distance`` bits, by chains."""
    fps = cut(fps.select("fp").distinct(), "fps", within)
    masks = block_masks(blocks or blocks_for(fps.count(), distance), distance)
    signed = [m - 2**64 if m >= 2**63 else m for m in masks]
    keyed = fps.select("fp", F.explode(F.array(*[F.struct(F.lit(j).alias("j"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for j, m in enumerate(signed)])).alias("t")).select("fp", "t.j", "t.key")
    # one shuffle of the keys; only those of several fingerprints go on
    shared = cut(keyed.withColumn("c", F.count(F.lit(1)).over(Window.partitionBy("j", "key"))).where("c > 1"), "blocks", within)
    light = shared.where(F.col("c") <= most).groupBy("j", "key").agg(F.collect_list("fp").alias("fps")).select("fps")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists, found = b.column(0), set()
            flat, at = lists.values.to_numpy(zero_copy_only=False), lists.offsets.to_numpy()
            for lo, hi in zip(at[:-1].tolist(), at[1:].tolist()):
                found.update(_linked(flat[lo:hi], distance))
            yield pa.RecordBatch.from_arrays([pa.array([e[i] for e in found], pa.int64()) for i in (0, 1)], names=["a", "b"])

    links = light.mapInArrow(compare, "a long, b long")
    dense = shared.where(F.col("c") > most).select("fp").distinct()

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        near, inner = near_words(distance + 1), len(near_words(distance))
        for b in batches:
            own = b.column(0).to_numpy(zero_copy_only=False)
            for lo in range(0, len(own), 256):
                part = own[lo:lo + 256]
                close = np.tile(np.arange(len(near)) < inner, len(part))
                yield pa.RecordBatch.from_arrays([pa.array((part[:, None] ^ near[None, :]).ravel(), pa.int64()), pa.array(np.repeat(part, len(near)), pa.int64()), pa.array(close)], names=["word", "fp", "close"])

    # A word is near at most len(near_words) fingerprints, so a list has that many members at most. The centre is within
    # d/2 bits rounded down, the others within d/2 rounded up (the same for an even d).
    stars = dense.mapInArrow(spread, "word long, fp long, close boolean").groupBy("word").agg(F.min(F.when(F.col("close"), F.col("fp"))).alias("a"), F.collect_list("fp").alias("fps"))
    stars = stars.where(F.col("a").isNotNull() & (F.size("fps") > 1)).select("a", F.explode("fps").alias("b")).where("a <> b")
    return links.union(stars).distinct()


def near_groups(docs: DataFrame, *, size: int = 4, distance: int = 4, blocks: int | None = None, most: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, fp, component_id`` of every row: the least id reachable over links of at most ``distance`` bits.

    Null text counts as empty; texts without words have fingerprint 0 and are linked like others; shorter texts than
    a shingle are one shingle. Texts are read whole, whatever their length; a bit that is set in just half the hashes
    is 0. Repeated rows and ids are kept as they are. An empty table gives an empty result. Other columns are ignored.
    """
    with scratch(docs.sparkSession) as at:
        fps = cut(fingerprints(docs, size=size, id_col=id_col, text_col=text_col), "fingerprints", at)
        # a fingerprint goes by the least id that has it, so a component's least node is its name
        least = cut(fps.groupBy("fp").agg(F.min("id").alias("least"), F.count(F.lit(1)).alias("c")), "least", at)
        links = fingerprint_links(least, distance=distance, blocks=blocks, most=most, within=at)
        for side in ("a", "b"):
            links = links.join(least.select(F.col("fp").alias(side), F.col("least").alias(f"l{side}")), side)
        labels = cut(components(links.select(F.col("la").alias("a"), F.col("lb").alias("b")), within=at), "labels", at)
        named = least.join(labels.withColumnRenamed("node", "least"), "least", "left").select("fp", "c", F.coalesce("label", "least").alias("component_id"))
        # fingerprints of very many rows (at most HOT_SHARE of them) are dealt out by salt
        hot_rows = max(HOT_LEAST, fps.count() // HOT_SHARE)
        salts = F.ceil(F.col("c") / hot_rows).cast("int")
        hot = F.broadcast(cut(least.where(F.col("c") > hot_rows).select("fp", salts.alias("salts")), "hot", at))
        dealt = fps.join(hot, "fp", "left").withColumn("salt", F.coalesce(F.pmod(F.xxhash64("id"), "salts"), F.lit(0)).cast("int")).drop("salts")
        spread = named.select("fp", "component_id", F.explode(F.sequence(F.lit(0), salts - 1)).alias("salt"))
        return cut(dealt.join(spread, ["fp", "salt"], "left").select("id", "fp", "component_id"), "groups")


def jaccard(a: list[int], b: list[int]) -> float:
    a, b = set(a), set(b)
    return len(a & b) / len(a | b) if a or b else 1.0


def shingle_set(text: str | None, size: int = 5) -> list[int]:
    """Hashes (signed) of the distinct shingles; those of a shorter text: one of all its words."""
    return shingle_array(text, size).tolist()


def shingle_array(text: str | None, size: int = 5) -> np.ndarray:
    """The same in rising order."""
    return np.unique(shingle_hashes(text, size).view("<i8"))


def _small(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Slices of ``id, text`` whose shingles take little memory."""
    for b in batches:
        yield from slices(b, 1, 256)


def common_shingles(docs: DataFrame, size: int, *, sample: int = 8192, most: int = 200_000) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that several of about ``sample`` documents ``id, text`` share, in rising order, and how many do."""
    some = docs.where(F.pmod(F.xxhash64("id"), F.lit(max(1, docs.count() // sample))) == 0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _small(batches):
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([shingle_array(t, size) for t in b.column(1).to_pylist()]), pa.int64())], names=["key"])

    found = some.mapInArrow(run, "key long").groupBy("key").agg(F.count(F.lit(1)).alias("c")).where("c > 2").orderBy(F.desc("c"), "key").limit(most).collect()
    keys, counts = np.array([r.key for r in found], dtype="<i8"), np.array([r.c for r in found], dtype="<i8")
    order = np.argsort(keys)
    return keys[order], counts[order]


def prefix(s: np.ndarray, similarity: float, late: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """The first of a set's shingles in an order that all sets share: two sets of ``similarity`` have one in common.

    Such sets share at least similarity * n members, so they cannot do without the first n - similarity * n + 1. Any
    common order will do; here shingles known to be common come last, so that few documents meet in a key.
    """
    keys, counts = late
    if not len(s):
        return np.zeros(1, dtype="<i8")
    rank = np.zeros(len(s), dtype="<i8")
    if len(keys):
        at = np.minimum(np.searchsorted(keys, s), len(keys) - 1)
        rank = np.where(keys[at] == s, counts[at], 0)
    return s[np.lexsort((s, rank))[:len(s) - ceil(similarity * len(s) - 1e-9) + 1]]


def parity(s: np.ndarray) -> bytes:
    """As many bits as the set has members (64 or the next power of two), each the parity of the members that fall on it.

    Two sets differ in at least as many members as their bits do, and folding the halves of the longer one onto each
    other gives its bits at half the length.
    """
    width = max(64, 1 << (len(s) - 1).bit_length()) if len(s) else 64
    return np.packbits(np.bincount((s.view("<u8") % np.uint64(width)).astype(np.int64), minlength=width) & 1, bitorder="little").tobytes()


def bits_apart(x: bytes, others: list[bytes]) -> np.ndarray:
    """In how many bits each of the others differs at the shorter length; lengths are the same or one is twice the other."""
    out = np.zeros(len(others), dtype=np.int64)
    own = np.frombuffer(x, dtype="<u8")
    sizes = np.array([len(y) for y in others])
    for size in np.unique(sizes):
        at = np.flatnonzero(sizes == size)
        them = np.frombuffer(b"".join([others[i] for i in at]), dtype="<u8").reshape(len(at), -1)
        me = own
        while me.shape[0] > them.shape[1]:
            me = me[:len(me) // 2] ^ me[len(me) // 2:]
        while them.shape[1] > len(me):
            them = them[:, :them.shape[1] // 2] ^ them[:, them.shape[1] // 2:]
        out[at] = np.bitwise_count(them ^ me).sum(1, dtype=np.int64)
    return out


def possible(n: np.ndarray, bits: list[bytes], i: int, j: np.ndarray, similarity: float) -> np.ndarray:
    """Those of ``j`` that can have the ``similarity`` with i by sizes ``n`` and parities: never lacks one that has."""
    most = (1 - similarity) / (1 + similarity) * (n[j] + n[i]) + 1e-6
    near = np.abs(n[j] - n[i]) <= most
    j, most = j[near], most[near]
    return j[bits_apart(bits[i], [bits[x] for x in j.tolist()]) <= most] if len(j) else j


def _runs(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.Table]:
    """Neighbouring rows that agree on the first ``keys`` (integer) columns, together, over the bounds of batches."""
    held: list[pa.RecordBatch] = []
    last = None
    for b in batches:
        if not b.num_rows:
            continue
        own = np.stack([b.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in range(keys)])
        edge = [0, *(np.flatnonzero((own[:, 1:] != own[:, :-1]).any(0)) + 1).tolist(), b.num_rows]
        for lo, hi in zip(edge[:-1], edge[1:]):
            if held and tuple(own[:, lo].tolist()) != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(b.slice(lo, hi - lo))
            last = tuple(own[:, lo].tolist())
    if held:
        yield pa.Table.from_batches(held)


def _some(ids: DataFrame) -> DataFrame:
    """A written table of ids, to be broadcast if it is short."""
    return F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids


def verified(docs: DataFrame, pairs: DataFrame, *, size: int, similarity: float, most: int, within: str) -> DataFrame:
    """The ``pairs(a, b)`` whose documents ``id, text`` have at least the ``similarity`` on shingle sets.

    Sets are sent once for each pair, to the pair's ``a``; an ``a`` of more than ``most`` pairs goes to several tasks.
    """
    kind = dict(docs.dtypes)["id"]
    load = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / most).cast("int").alias("salts"))
    own = load.select(F.col("a").alias("id"), F.col("a").alias("to"), F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), F.lit(0).alias("role"))
    other = pairs.join(load, "a").select(F.col("b").alias("id"), F.col("a").alias("to"), F.pmod(F.hash("b"), "salts").alias("salt"), F.lit(1).alias("role"))
    routes = cut(own.union(other).groupBy("id").agg(F.collect_list(F.struct("to", "salt", "role")).alias("routes")), "routes", within)

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _small(batches):
            packed = [shingle_array(t, size).tobytes() for t in b.column(1).to_pylist()]
            lists = b.column(2)
            row = np.repeat(np.arange(b.num_rows), np.diff(lists.offsets.to_numpy()))
            to, salt, role = lists.flatten().flatten()
            for lo in range(0, len(row), 256):
                part = row[lo:lo + 256]
                yield pa.RecordBatch.from_arrays([to[lo:lo + 256], salt[lo:lo + 256], role[lo:lo + 256], b.column(0).take(pa.array(part)), pa.array([packed[i] for i in part], pa.binary())], names=["to", "salt", "role", "id", "s"])

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        centre: np.ndarray | None = None
        for b in batches:
            good = []
            for i, (role, raw) in enumerate(zip(b.column(2).to_pylist(), b.column(4))):
                s = np.frombuffer(raw.as_buffer(), dtype="<i8")
                if role == 0:
                    centre = s.copy()
                    continue
                both = int((centre[np.minimum(np.searchsorted(centre, s), len(centre) - 1)] == s).sum()) if len(centre) and len(s) else 0
                if both >= similarity * (len(centre) + len(s) - both):
                    good.append(i)
            found = b.take(pa.array(good, pa.int64()))
            yield pa.RecordBatch.from_arrays([found.column(0), found.column(3)], names=["a", "b"])

    sent = docs.join(_some(routes), "id").select("id", "text", "routes").mapInArrow(send, f"to {kind}, salt int, role int, id {kind}, s binary")
    return cut(sent.repartition("to", "salt").sortWithinPartitions("to", "salt", "role").mapInArrow(check, f"a {kind}, b {kind}"), "similar", within)


def near_copies(docs: DataFrame, *, size: int = 5, similarity: float = 0.8, distance: int = 4, most: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``id, component_id`` of ids that have a near copy: links are pairs of at least ``similarity`` on word shingles.

    SimHash first: rows of one fingerprint (of ``size``-word shingles) with the least id of it, and the links between
    fingerprints that differ in at most ``distance`` bits, as ``near_groups`` finds them. The rest is exact, too: every
    pair with that Jaccard similarity shares a key of its prefixes. These candidates
    are taken in three turns, each leaving out pairs that verified links have connected by then: every id with the
    least id of its keys; every other pair with the least id of a key, and in each key pairs that would connect its
    members; last, all pairs of a key that are still apart. In a key, members are compared by size and parities, in
    tiles of about ``most``, which rules out pairs for certain; the rest is held against the exact similarity. Rows of
    one id count as one document. Null text counts as empty; texts without words are near copies of each other. Texts
    are read whole. An empty table gives an empty result.
    """
    with scratch(docs.sparkSession) as at:
        links = _near_links(docs.select(quoted(id_col).alias("id"), quoted(text_col).alias("text")), size, similarity, distance, most, at)
        return cut(components(links, within=at).select(F.col("node").alias("id"), F.col("label").alias("component_id")), "near-copies")


def _fingerprint_pairs(own: DataFrame, distance: int, most: int, at: str) -> DataFrame:
    """Pairs ``a, b`` of ``id, fp`` rows: each with the least id of its fingerprint, and least ids of linked fingerprints."""
    kind = dict(own.dtypes)["id"]
    least = cut(own.groupBy("fp").agg(F.min("id").alias("least"), F.count(F.lit(1)).alias("c")), "least", at)
    # fingerprints of very many rows (at most HOT_SHARE of them) come to their rows
    hot = F.broadcast(cut(least.where(F.col("c") > max(HOT_LEAST, own.count() // HOT_SHARE)).select("fp", "least"), "hot", at))
    few = least.join(hot, "fp", "left_anti").where("c > 1").select("fp", "least")
    same = own.join(hot, "fp").union(own.join(hot, "fp", "left_anti").join(few, "fp")).where("id <> least").select(F.col("least").alias("a"), F.col("id").alias("b"))
    links = fingerprint_links(least, distance=distance, most=most, within=at)
    for side in ("a", "b"):
        links = links.join(least.select(F.col("fp").alias(side), F.col("least").alias(f"l{side}")), side)
    apart = links.select(F.least("la", "lb").cast(kind).alias("a"), F.greatest("la", "lb").cast(kind).alias("b")).where("a <> b")
    return cut(same.union(apart).distinct(), "fingerprint-pairs", at)


def _near_links(docs: DataFrame, size: int, similarity: float, distance: int, most: int, at: str) -> DataFrame:
    kind = dict(docs.dtypes)["id"]
    late = common_shingles(docs, size)

    def sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _small(batches):
            hashes = [shingle_hashes(t, size) for t in b.column(1).to_pylist()]
            sets, fps = [np.unique(h.view("<i8")) for h in hashes], np.array([majority(h) for h in hashes], dtype="<u8")
            columns = [b.column(0), pa.array(fps.view("<i8"), pa.int64()), pa.array([len(s) for s in sets], pa.int32()), pa.array([parity(s) for s in sets], pa.binary()), pa.array([prefix(s, similarity, late) for s in sets], pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(columns, names=["id", "fp", "n", "bits", "keys"])

    own = cut(docs.mapInArrow(sketch, f"id {kind}, fp long, n int, bits binary, keys array<long>"), "sketches", at)
    key = Window.partitionBy("key")
    keyed = own.select("id", F.explode("keys").alias("key"))
    met = keyed.select("id", F.count(F.lit(1)).over(key).alias("c"), F.min("id").over(key).alias("top"), F.bit_xor(F.xxhash64("id")).over(key).alias("xor")).where("c > 1")
    # a passage gives many keys with the same members: one of them will do
    shared = cut(met.select("id", "c", "top", F.xxhash64("c", "top", "xor").alias("key")).distinct(), "shared-keys", at)

    def rule_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            na, nb = (b.column(c).to_numpy(zero_copy_only=False) for c in (2, 3))
            most = (1 - similarity) / (1 + similarity) * (na + nb) + 1e-6
            may = np.abs(na - nb) <= most
            at = np.flatnonzero(may)
            may[at] = [bits_apart(x, [y])[0] <= m for x, y, m in zip(b.column(4).take(pa.array(at)).to_pylist(), b.column(5).take(pa.array(at)).to_pylist(), most[at])]
            yield b.select([0, 1]).filter(pa.array(may))

    def check(pairs: DataFrame) -> DataFrame:
        return verified(docs, pairs, size=size, similarity=similarity, most=most, within=at)

    def labels(links: DataFrame) -> DataFrame:
        return cut(components(links, within=at).select(F.col("node").alias("id"), "label"), "labels", at)

    def apart(pairs: DataFrame, now: DataFrame) -> DataFrame:
        named = pairs
        for side in ("a", "b"):
            named = named.join(now.select(F.col("id").alias(side), F.col("label").alias(f"l{side}")), side, "left")
        return named.where(F.coalesce("la", "a") != F.coalesce("lb", "b")).select("a", "b")

    def members(now: DataFrame, thin: bool) -> DataFrame:
        """Possible pairs of members of one key that have no link yet; ``thin``: only so many as would connect them."""
        left = shared.where("c > 2 and id <> top").select("key", "id").distinct().join(now, "id", "left").select("key", "id", F.coalesce("label", "id").alias("label"))
        mixed = left.groupBy("key").agg(F.count(F.lit(1)).alias("m"), F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo < hi").select("key", F.ceil(F.col("m") / most).cast("int").alias("tiles"))
        tiled = left.join(mixed, "key").withColumn("tile", F.pmod(F.hash("id"), "tiles")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
        dealt = tiled.join(own.select("id", "n", "bits"), "id").select("key", F.least("tile", "other").alias("lo"), F.greatest("tile", "other").alias("hi"), "id", "label", "n", "tile", "bits")
        # one group's members are held at a time: rows come sorted by group, not gathered into lists
        dealt = dealt.repartition("key", "lo", "hi").sortWithinPartitions("key", "lo", "hi")

        def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for group in _runs(batches, 3):
                ids, label, n, tile = (group.column(c).to_numpy() for c in ("id", "label", "n", "tile"))
                bits, whole = group.column("bits").to_pylist(), group.column("lo")[0].as_py() == group.column("hi")[0].as_py()
                now, a, b = label.copy(), [], []
                for i in range(len(ids) - 1):
                    j = np.arange(i + 1, len(ids))
                    j = j[(now[j] != now[i]) & (whole | (tile[j] != tile[i]))]
                    j = possible(n, bits, i, j, similarity)
                    if thin and len(j):  # the first of each part; what they would connect counts as one part from here on
                        parts, first = np.unique(now[j], return_index=True)
                        j = j[first]
                        now[np.isin(now, parts)] = now[i]
                    a.append(np.minimum(ids[i], ids[j])), b.append(np.maximum(ids[i], ids[j]))
                if sum(map(len, a)):
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x), group.column("id").type) for x in (a, b)], names=["a", "b"])

        return dealt.mapInArrow(compare, f"a {kind}, b {kind}")

    tested = _fingerprint_pairs(own.select("id", "fp"), distance, most, at)
    links = check(tested)
    now = labels(links)
    star = apart(shared.where("id <> top").select(F.col("top").alias("a"), F.col("id").alias("b")).distinct().join(tested, ["a", "b"], "left_anti"), now)
    one, other = own.select(F.col("id").alias("a"), F.col("n").alias("na"), F.col("bits").alias("ba")), own.select(F.col("id").alias("b"), F.col("n").alias("nb"), F.col("bits").alias("bb"))
    star = cut(star.join(one, "a").join(other, "b").select("a", "b", "na", "nb", "ba", "bb").mapInArrow(rule_out, f"a {kind}, b {kind}"), "star", at)
    first = cut(star.groupBy("b").agg(F.min("a").alias("a")).select("a", "b"), "pairs", at)
    if first.take(1):
        links, tested = links.union(check(first)), tested.union(first)
        now = labels(links)
    second = cut(apart(star, now).union(members(now, True)).distinct().join(tested, ["a", "b"], "left_anti"), "pairs", at)
    if second.take(1):
        links, tested = links.union(check(second)), tested.union(second)
        now = labels(links)
        third = cut(members(now, False).distinct().join(tested, ["a", "b"], "left_anti"), "pairs", at)
        if third.take(1):
            links = links.union(check(third))
    return links


def drop_near_copies(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **params) -> DataFrame:
    """``docs`` without the rows of ids that are a near copy of a smaller id; columns unchanged, whatever their names."""
    found = near_copies(docs, id_col=id_col, text_col=text_col, **params)
    gone = _some(found.where("component_id <> id").select("id"))  # if few are broadcast, the texts stay where they are
    inner = [f"c{i}" for i in range(len(docs.columns))]
    own = inner[docs.columns.index(id_col)]
    return docs.toDF(*inner).join(gone.withColumnRenamed("id", "gone"), F.col(own) == F.col("gone"), "left_anti").toDF(*docs.columns)
