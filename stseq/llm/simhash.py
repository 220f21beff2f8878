"""SimHash fingerprints and near-duplicate components with pigeonring candidate filtering.

Fingerprint: bit b of 64 is set if more than half of a text's shingle hashes have bit b set.

Candidates: the 64 bits form a ring of 16 segments of 4 bits. If two fingerprints differ in at most 3 bits,
then some start segment exists from which every run of l segments differs in at most floor(3*l/16) bits.
So the first five segments are equal (20 bits) and the next five differ in at most one bit, hence one of
their two halves (10 bits) is equal as well. Each fingerprint therefore has 16*2 keys of 30 bits, and any
two linked ones share a key. Pairs of a bucket then pass the full ring test from the bucket's start before
their Hamming distance is taken.

Buckets hold distinct fingerprints only (equal ones meet in one pre-aggregated row). A bucket gives the
edges of a spanning forest of its links, not all its pairs; one of more than ``BLOCK`` fingerprints is dealt
over tasks that hold two blocks each, so that every pair of the bucket meets in exactly one of them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stseq.llm.common import connected_components, shared_buckets, stored
from stseq.llm.textblock import Words, blocks, shingle_hashes

SEGMENTS, SEGMENT_BITS = 16, 4
BLOCK = 2048
_ALL = (1 << 64) - 1


def text_fingerprints(texts: pa.Array, words: int = 3) -> np.ndarray:
    """64-bit fingerprints (uint64) of a binary column of texts, over XXH64 (seed 42) of space-joined word shingles."""
    out = np.zeros(len(texts), np.uint64)
    for at, _, data, offsets in blocks(texts):
        w = Words(data, offsets)
        raw = w.data.tobytes()
        starts, ends = w.starts.tolist(), w.ends.tolist()
        plain = bool(len(w) < 2) or bool(((w.starts[1:] - w.ends[:-1] == 1) & (w.data[w.ends[:-1]] == 0x20))[_inner(w)].all())
        digest = xxhash.xxh64_intdigest
        for i in range(len(offsets) - 1):
            a, b = int(w.first[i]), int(w.first[i + 1])
            if a == b:
                continue
            k = min(words, b - a)
            if plain:  # single spaces in all texts: shingles are slices
                h = [digest(raw[s:e], 42) for s, e in zip(starts[a : b - k + 1], ends[a + k - 1 : b])]
            else:
                joined = b" ".join(raw[starts[a] : ends[b - 1]].split())
                size = w.ends[a:b] - w.starts[a:b]
                stop = np.cumsum(size + 1) - 1
                begin = (stop - size).tolist()
                stop = stop.tolist()
                h = [digest(joined[s:e], 42) for s, e in zip(begin[: b - a - k + 1], stop[k - 1 :])]
            out[at + i] = majority(np.array(h, np.uint64))
    return out


def _inner(w: Words) -> np.ndarray:
    """Which gaps between successive words lie inside one text."""
    inside = np.ones(max(len(w) - 1, 0), bool)
    edge = w.first[1:-1]
    inside[edge[(edge > 0) & (edge < len(w))] - 1] = False
    return inside


def majority(hashes: np.ndarray) -> int:
    """Bits set in over half of the hashes."""
    total = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 14):
        bits = np.unpackbits(hashes[at : at + (1 << 14)].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
        total += bits.sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(total * 2 > len(hashes)).tobytes(), "big")


def with_fingerprint(docs: DataFrame, words: int = 3, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """``id_col`` and ``fp`` (the fingerprint as a signed long) of each row; null text counts as empty (0)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = text_fingerprints(b.column(1), words)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp.view(np.int64))], names=[id_col, "fp"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, F.col(text).cast("binary")).mapInArrow(run, f"{id_col} {kind}, fp bigint")


def _turned(fp: Column, start: int) -> Column:
    """The ring read from segment ``start``."""
    s = start * SEGMENT_BITS
    return fp if s == 0 else F.shiftleft(fp, s).bitwiseOR(F.shiftrightunsigned(fp, 64 - s))


def ring_keys(fp: Column) -> Column:
    """Array of the 32 bucket keys: 20 bits of five equal segments, ten of one half of the next five, the key's number."""
    keys = []
    for start in range(SEGMENTS):
        ring = _turned(fp, start)
        head = F.shiftrightunsigned(ring, 44)
        for half in (0, 1):
            tail = F.shiftrightunsigned(ring, 34 - 10 * half).bitwiseAND(F.lit(1023))
            keys.append(F.shiftleft(head, 16).bitwiseOR(F.shiftleft(tail, 6)).bitwiseOR(F.lit(start * 2 + half)))
    return F.array(*keys)


_POP = np.array([bin(i).count("1") for i in range(16)], np.int8)


def ring_test(xor: np.ndarray, start: np.ndarray, limit: int = 3) -> np.ndarray:
    """Whether each run from segment ``start`` stays within its share of ``limit`` differing bits."""
    ok = np.ones(len(xor), bool)
    total = np.zeros(len(xor), np.int16)
    for l in range(1, SEGMENTS + 1):
        seg = (start + l - 1) % SEGMENTS
        nibble = (xor >> ((SEGMENTS - 1 - seg) * SEGMENT_BITS).astype(np.uint64)) & np.uint64(15)
        total += _POP[nibble.astype(np.int64)]
        ok &= total <= limit * l // SEGMENTS
    return ok


def _linked(a: np.ndarray, b: np.ndarray, start: np.ndarray, limit: int) -> np.ndarray:
    xor = a ^ b
    ok = ring_test(xor, start, limit)
    ok[ok] = np.bitwise_count(xor[ok]) <= limit
    return ok


def bucket_forest(fp: np.ndarray, side: np.ndarray, start: int, limit: int) -> list[tuple[int, int]]:
    """Edges that span the links of one bucket. ``side``: 0 and 1 for two blocks of which only cross pairs count, else 2."""
    edges, left = [], np.arange(len(fp))
    while len(left):
        todo, left = [left[0]], left[1:]
        while todo and len(left):
            at = todo.pop()
            far = left[side[left] != side[at]] if side[at] != 2 else left
            hit = far[_linked(fp[far], np.full(len(far), fp[at]), np.full(len(far), start), limit)]
            edges += [(int(fp[at]), int(x)) for x in fp[hit]]
            todo += hit.tolist()
            left = left[~np.isin(left, hit)] if len(hit) else left
    return edges


def _edges(frames: Iterator[pd.DataFrame], limit: int) -> Iterator[pd.DataFrame]:
    """Spanning edges of the buckets of one task; its rows come sorted by bucket and block."""
    carry = None

    def solve(key, part, fp, side):
        new = np.ones(len(key), bool)
        new[1:] = (key[1:] != key[:-1]) | (part[1:] != part[:-1])
        begin = np.flatnonzero(new)
        size = np.diff(np.append(begin, len(key)))
        start = (key & 63) // 2
        src, dst = [], []
        # pairs of buckets of 2 to 8 rows, one lag at a time over all of them
        end = np.repeat(begin + size, size)
        small = np.repeat(size <= 8, size)
        for lag in range(1, 8):
            at = np.flatnonzero(small[: max(len(key) - lag, 0)] & (np.arange(len(key))[: max(len(key) - lag, 0)] + lag < end[: max(len(key) - lag, 0)]))
            if not len(at):
                break
            ok = _linked(fp[at], fp[at + lag], start[at], limit) & ((side[at] != side[at + lag]) | (side[at] == 2))
            src.append(fp[at[ok]])
            dst.append(fp[at[ok] + lag])
        for b, n in zip(begin[size > 8].tolist(), size[size > 8].tolist()):
            found = bucket_forest(fp[b : b + n], side[b : b + n], int(start[b]), limit)
            if found:
                e = np.array(found, np.uint64)
                src.append(e[:, 0])
                dst.append(e[:, 1])
        if src:
            s, d = np.concatenate(src).view(np.int64), np.concatenate(dst).view(np.int64)
            return pd.DataFrame({"src": np.minimum(s, d), "dst": np.maximum(s, d)}).drop_duplicates()
        return None

    for f in frames:
        if carry is not None:
            f = pd.concat([carry, f], ignore_index=True)
        key, part = f["key"].to_numpy(), f["part"].to_numpy()
        last = np.flatnonzero((key == key[-1]) & (part == part[-1]))[0]
        carry = f.iloc[last:]
        if last:
            out = solve(key[:last], part[:last], f["fp"].to_numpy()[:last].view(np.uint64), f["side"].to_numpy()[:last])
            if out is not None:
                yield out
    if carry is not None:
        out = solve(carry["key"].to_numpy(), carry["part"].to_numpy(), carry["fp"].to_numpy().view(np.uint64), carry["side"].to_numpy())
        if out is not None:
            yield out


def near_edges(distinct: DataFrame, limit: int = 3, block: int = BLOCK) -> DataFrame:
    """Edges (src, dst) that connect what differs in at most ``limit`` (3 or fewer) bits among distinct fingerprints ``fp``."""
    if not 0 <= limit <= 3:
        raise ValueError("the keys hold for at most three differing bits")
    keyed = distinct.select("fp", F.explode(ring_keys(F.col("fp"))).alias("key"))
    rows = shared_buckets(keyed, ["key"], "fp", block)
    # block i meets blocks j >= i in part i*parts+j; within part (i, i) all pairs count, else the cross pairs
    rows = rows.select(
        "key", "fp", "own", "parts", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("other")
    ).select(
        "key",
        (F.least("own", "other").cast("long") * F.col("parts") + F.greatest("own", "other")).alias("part"),
        F.when(F.col("own") == F.col("other"), 2).when(F.col("own") < F.col("other"), 0).otherwise(1).cast("int").alias("side"),
        "fp",
    )
    dealt = rows.repartition("key", "part").sortWithinPartitions("key", "part")
    return dealt.mapInPandas(lambda it: _edges(it, limit), "src bigint, dst bigint").distinct()


def simhash_components(docs: DataFrame, words: int = 3, limit: int = 3, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """Per row: ``id_col``, ``fingerprint`` (16 hex digits) and ``component_id``, the smallest id reachable over links.

    Nulls and empty texts have fingerprint zero and link like any other; repeated rows stay, each with its
    component; an empty table gives an empty result. Other columns of ``docs`` are not read.
    """
    prints = stored(with_fingerprint(docs, words, text, id_col), "simhash")
    distinct = stored(prints.groupBy("fp").agg(F.min(id_col).alias("low")), "simhash-distinct")
    parts = connected_components(near_edges(distinct, limit))
    # smallest document of each component of fingerprints
    joined = distinct.join(parts.select(F.col("node").alias("fp"), "component"), "fp", "left")
    joined = joined.withColumn("component", F.coalesce("component", "fp"))
    lowest = joined.groupBy("component").agg(F.min("low").alias("component_id"))
    of_print = joined.join(lowest, "component").select("fp", "component_id")
    return prints.join(of_print, "fp").select(id_col, F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame) -> DataFrame:
    """One row of each group of near-duplicates (fingerprints within 3 bits, or 5-word shingles alike by 0.8 or more): see :mod:`stseq.llm.neardup`."""
    from stseq.llm import neardup

    return neardup.keep_one(docs)
