"""SimHash near-duplicates by meet-in-the-middle ball hashing.

Two fingerprints link at 3 or fewer differing bits. The 64 bits fall into three blocks; of two linked fingerprints at
most two differing bits lie outside the block in which they differ most. So with that block masked, each side flips at
most one further bit (half of the radius that is left) and both emit the same variant: 131 variants for a fingerprint, shuffled once.
Fingerprints meet in variant buckets and are verified there. A bucket of up to `bucket_limit` fingerprints gives a
spanning forest of its verified links. Members of larger buckets are hashed again with whole balls of
radius 1 and 2 around unmasked fingerprints, where the first radius-1 member of a bucket links to all the others without pair comparison,
so cost stays linear in the fingerprints and no link is lost.

Nulls and empty texts have fingerprint zero and link like any other; texts of any length are read whole; repeated rows share a fingerprint, and the least id names a component, so
there are no ties; extra columns, whatever their names, are ignored; an empty table gives an empty result; a null id never becomes a component id unless all ids of the component are null.
"""

from __future__ import annotations

from functools import partial

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, joined_hot, stored

SEED, SHINGLE, RADIUS = 42, 3, 3
BLOCKS = (0x1FFFFF, 0x1FFFFF << 21, 0x3FFFFF << 42)
_digest = partial(xxhash.xxh64_intdigest, seed=SEED)
_STEP = 1 << 16


def fingerprint(text: str | None) -> int:
    """Unsigned fingerprint of a whole text."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    shingles = zip(*(words[i:] for i in range(SHINGLE))) if len(words) >= SHINGLE else [words]
    total = max(1, len(words) - SHINGLE + 1)
    digests = map(_digest, map(b" ".join, shingles))
    votes = np.zeros(64, np.int64)
    for begin in range(0, total, _STEP):
        part = np.fromiter(digests, np.uint64, min(_STEP, total - begin))
        votes += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(votes * 2 > total, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp): one row per row of docs, its id of any type that has an order; fp holds the unsigned fingerprint in a long."""

    def run(batches):
        for batch in batches:
            prints = np.array([fingerprint(t) for t in batch.column(1).to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(prints.view(np.int64), pa.int64())], ["doc_id", "fp"])

    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, fp long")


def _flips(mask: int) -> np.ndarray:
    return np.array([0, *(1 << j for j in range(64) if not mask >> j & 1)], np.uint64)


def masked_variants(distinct: DataFrame) -> DataFrame:
    """(variant, fp): for each block, the fingerprint without it and all its one-bit flips elsewhere."""

    def run(batches):
        for batch in batches:
            fp = batch.column(0).to_numpy().view(np.uint64)
            for begin in range(0, len(fp), 512):
                part = fp[begin : begin + 512]
                made = [((part & np.uint64(~m & (1 << 64) - 1))[:, None] ^ _flips(m)[None, :]) for m in BLOCKS]
                variant = np.concatenate(made, axis=1)
                owner = np.repeat(part, variant.shape[1])
                yield pa.RecordBatch.from_arrays([pa.array(variant.ravel().view(np.int64)), pa.array(owner.view(np.int64))], ["variant", "fp"])

    return distinct.select("fp").mapInArrow(run, "variant long, fp long")


def whole_variants(heavy: DataFrame) -> DataFrame:
    """(variant, far, fp): the whole ball of radius 2 around each fingerprint; far marks distance 2."""
    one = [1 << j for j in range(64)]
    two = [a | b for i, a in enumerate(one) for b in one[i + 1 :]]
    flips, far = np.array([0, *one, *two], np.uint64), np.array([False] * 65 + [True] * len(two))

    def run(batches):
        for batch in batches:
            fp = batch.column(0).to_numpy().view(np.uint64)
            for begin in range(0, len(fp), 32):
                part = fp[begin : begin + 32]
                variant = (part[:, None] ^ flips[None, :]).ravel()
                yield pa.RecordBatch.from_arrays(
                    [pa.array(variant.view(np.int64)), pa.array(np.tile(far, len(part))), pa.array(np.repeat(part, len(flips)).view(np.int64))], ["variant", "far", "fp"]
                )

    return heavy.select("fp").mapInArrow(run, "variant long, far boolean, fp long")


class _Forest:
    """Passes on only links that join two sets of those seen so far; forgets all beyond a bounded number of members."""

    def __init__(self, room: int = 1 << 20):
        self.above: dict[int, int] = {}
        self.room = room

    def top(self, x: int) -> int:
        above = self.above
        while (up := above.get(x, x)) != x:
            above[x] = x = above.get(up, up)
        return x

    def joins(self, a: int, b: int) -> bool:
        if len(self.above) > self.room:
            self.above.clear()
        a, b = self.top(a), self.top(b)
        if a == b:
            return False
        self.above[max(a, b)] = min(a, b)
        return True


def _spanning(members: np.ndarray) -> list[tuple[int, int]]:
    """A spanning forest of the links among a bucket's distinct fingerprints."""
    links, rest = [], members
    while len(rest) > 1:
        front, rest = [rest[0]], rest[1:]
        while front and len(rest):
            at = front.pop()
            near = np.bitwise_count(rest ^ at) <= RADIUS
            if near.any():
                front += list(rest[near])
                links += [(int(at), int(x)) for x in rest[near]]
                rest = rest[~near]
    return links


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _links_of_buckets(limit: int):
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("heavy", pa.bool_())])

    def run(batches):
        forest = _Forest()
        held_key, held, overfull = None, np.empty(0, np.uint64), False

        def closed(members):
            return [x for x in _spanning(np.unique(members)) if forest.joins(*x)] if len(members) > 1 else []

        for batch in batches:
            key, fp = batch.column(0).to_numpy(), batch.column(1).to_numpy().view(np.uint64)
            if not len(key):
                continue
            out: list[tuple[int, int]] = []
            heavy: list[np.ndarray] = []
            starts = np.concatenate([[0], np.flatnonzero(key[1:] != key[:-1]) + 1, [len(key)]])
            first = starts[1] if key[0] == held_key else 0
            if first:
                held = np.concatenate([held, fp[:first]])
                if overfull or len(held) > limit:
                    heavy.append(held)
                    held, overfull = held[:0], True
            if first < len(key):
                if not overfull:
                    out += closed(held)
                held_key, overfull = key[-1], False
                begins, ends = starts[:-1], starts[1:]
                inner = (begins >= first) & (ends < len(key)) & (ends - begins > 1)
                for lo, hi in zip(begins[inner], ends[inner]):
                    if hi - lo > limit:
                        heavy.append(fp[lo:hi])
                    else:
                        out += closed(fp[lo:hi])
                held = fp[begins[-1] :].copy()
                if len(held) > limit:
                    heavy.append(held)
                    held, overfull = held[:0], True
            flagged = np.unique(np.concatenate(heavy)) if heavy else np.empty(0, np.uint64)
            ends_ = np.array(out, np.uint64).reshape(-1, 2)
            a, b = np.concatenate([ends_[:, 0], flagged]).view(np.int64), np.concatenate([ends_[:, 1], flagged]).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(np.arange(len(a)) >= len(ends_))], schema=schema)
        last = [] if overfull else closed(held)
        yield pa.RecordBatch.from_arrays([pa.array([_signed(x[0]) for x in last], pa.int64()), pa.array([_signed(x[1]) for x in last], pa.int64()), pa.array([False] * len(last), pa.bool_())], schema=schema)

    return run


def _links_of_hubs(batches):
    """Rows sorted by (variant, far, fp): where the first of a variant is within distance 1, every other one is within 3 of it."""
    forest, held = _Forest(), None  # the variant that a batch may share with the next one, its first fingerprint, and whether that is near
    for batch in batches:
        key, far, fp = batch.column(0).to_numpy(), batch.column(1).to_numpy(zero_copy_only=False), batch.column(2).to_numpy()
        if not len(key):
            continue
        begins = np.concatenate([[0], np.flatnonzero(key[1:] != key[:-1]) + 1])
        hub, near = fp[begins].copy(), ~far[begins]
        if held is not None and held[0] == key[0]:
            hub[0], near[0] = held[1], held[2]
        held = (key[-1], hub[-1], near[-1])
        sizes = np.diff(np.concatenate([begins, [len(key)]]))
        hubs, mine = np.repeat(hub, sizes), np.repeat(near, sizes)
        some = mine & (hubs != fp)
        pairs = np.unique(np.stack([hubs[some], fp[some]], axis=1), axis=0)
        out = np.array([x for x in pairs.tolist() if forest.joins(*x)], np.int64).reshape(-1, 2)
        yield pa.RecordBatch.from_arrays([pa.array(out[:, 0]), pa.array(out[:, 1])], ["a", "b"])


def links(distinct: DataFrame, bucket_limit: int = 2048) -> DataFrame:
    """(a, b), a < b: links among distinct fingerprints with the same components as all links within RADIUS."""
    dealt = masked_variants(distinct).repartition("variant").sortWithinPartitions("variant", "fp")
    found = stored(dealt.mapInArrow(_links_of_buckets(bucket_limit), "a long, b long, heavy boolean").distinct(), "simhash-links")
    pairs = found.filter(~F.col("heavy")).select("a", "b")
    heavy = found.filter("heavy").select(F.col("a").alias("fp")).distinct()
    if not heavy.isEmpty():
        hubs = whole_variants(heavy).repartition("variant").sortWithinPartitions("variant", "far", "fp")
        pairs = pairs.unionByName(hubs.mapInArrow(_links_of_hubs, "a long, b long"))
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, root): the smallest node reachable, for every node of edges (a, b); alternating star contraction.

    Each round points all larger neighbours of a node at the smallest one, then all smaller ones; rounds grow with
    the logarithm of the longest path. Only aggregates of one row reach the driver.
    """

    def smallest(e):
        return e.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n"))

    def mark(e):
        return tuple(e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    now = cut(edges.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    seen = None
    while (m := mark(now)) != seen and m[0]:
        seen = m
        both = now.union(now.select("v", "u"))
        large = joined_hot(both, smallest(both), "u").filter("v > u").select(F.col("v").alias("u"), F.least("m", "u").alias("v")).distinct()
        low = large.filter("u > v")
        small = joined_hot(low, smallest(low), "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e")).select("e.u", "e.v")
        now = cut(small.filter("u > v").distinct())
    found = now.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return found.unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bucket_limit: int = 2048) -> DataFrame:
    """(doc_id, fp, component_id): one row per row of docs."""
    printed = stored(fingerprints(docs, id_col, text_col), "simhash-prints")
    distinct = stored(printed.groupBy("fp").agg(F.min("doc_id").alias("least_id"), F.count(F.lit(1)).alias("n")), "simhash-distinct")
    roots = components(links(distinct, bucket_limit)).withColumnRenamed("node", "fp")
    owned = distinct.join(roots, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    named = owned.groupBy("root").agg(F.min("least_id").alias("component_id"))
    sized = named.join(owned.groupBy("root").agg(F.count(F.lit(1)).alias("n")), "root")
    owned = joined_hot(owned.select("fp", "root", F.col("n").alias("rows")), sized, "root").select("fp", "component_id", F.col("rows").alias("n"))
    return joined_hot(printed, stored(owned, "simhash-owned"), "fp").select("doc_id", "fp", "component_id")


def hexadecimal(fp):
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
