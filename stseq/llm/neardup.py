"""Near-duplicate components by SimHash fingerprints and by a Jaccard similarity of word shingles, both by pigeonring filtering.

Texts link if their 64-bit SimHash fingerprints (3-word shingles) differ in at most ``BITS`` bits: :mod:`stseq.llm.simhash` gives
the keys, the ring test and the Hamming distances, and loses no pair.

They link as well at a similarity of 0.8 in 5-word shingles. There two fingerprints differ in about 10 bits, where no exact
candidate search stays selective, so for these links the ring is laid over another sketch: ``SEGMENTS`` segments of ``RUN`` min-wise
hashes of a text's shingles, in which two texts agree at each position with a probability of their similarity. If two sketches differ in
at most ``LIMIT`` positions (fewer than there are segments), some start segment exists from which every run of l
segments differs in at most floor(LIMIT*l/SEGMENTS) positions; the first one is equal. So texts with an equal segment
share a bucket, the chain test from that segment prunes the pairs of the bucket, and loses none within the limit. A pair
of similarity 0.8 differs in more positions with a probability of 0.5 percent, one of 0.85 of 0.01 percent.

Equal texts are one text. A bucket gives the edges of a spanning forest of what passes its ring or chain test; these edges form
clusters, a shingle set and a fingerprint go to their cluster once, and the links within a cluster are taken exactly. A link by
fingerprints needs a common shingle: very short texts may agree in 61 bits by chance. Buckets and clusters are
cut into blocks of ``BLOCK`` texts; one of any size is dealt over tasks that hold two blocks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stseq.llm.common import checked_small, connected_components, shared_buckets, stored
from stseq.llm.simhash import near_edges, text_fingerprints
from stseq.llm.textblock import Words, blocks, give_back, mix, shingle_hashes

SHINGLE, SIMILARITY = 5, 0.8
#: Words of a fingerprint's shingles, and bits in which the fingerprints of linked texts may differ.
PRINT_SHINGLE, BITS = 3, 3
#: Segments of the ring, min-wise hashes in each, and positions in which linked sketches may differ.
SEGMENTS, RUN, LIMIT = 24, 3, 23
BLOCK = 512
_FACTORS = mix(np.arange(101, 101 + SEGMENTS * RUN, dtype=np.uint64)) | np.uint64(1)


def with_sketch(docs: DataFrame, words: int = SHINGLE) -> DataFrame:
    """doc_id, content (hash of the text's lower-cased words), bands (hash of each segment), marks (16 bits of each min-wise
    hash, binary), both empty without words, and fp (the SimHash fingerprint as a signed long).
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            content, bands, lens, marks = [], [], [], []
            for _, _, data, offsets in blocks(b.column(1)):
                w = Words(data, offsets)
                h, at = shingle_hashes(w.hashes(), w.first, words)
                some = np.diff(at) > 0
                begins = at[:-1][some]
                part = np.zeros((int(some.sum()), SEGMENTS), np.uint64)
                mark = np.zeros((len(part), SEGMENTS * RUN), np.uint16)
                if len(h):
                    for j in range(SEGMENTS):
                        for i in range(RUN):
                            low = np.minimum.reduceat(h * _FACTORS[j * RUN + i], begins)
                            mark[:, j * RUN + i] = mix(low) >> np.uint64(48)
                            part[:, j] = mix(part[:, j] * np.uint64(31) + low + np.uint64(j))
                own = iter(mark)
                marks += [next(own).tobytes() if x else b"" for x in some.tolist()]
                whole = np.zeros(len(some), np.uint64)
                if len(h):
                    place = np.arange(len(h)) - np.repeat(at[:-1], np.diff(at))
                    # the sequence of shingles, not their set: differing texts of equal sets stay apart and link
                    whole[some] = mix(np.add.reduceat(mix(h + place.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)), begins) + np.diff(at)[some].astype(np.uint64))
                content.append(whole)
                lens.append(np.where(some, SEGMENTS, 0))
                bands.append(part.ravel())
            if not content:
                continue
            ends = np.concatenate([[0], np.cumsum(np.concatenate(lens))]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(bands).view(np.int64)))
            fp = pa.array(text_fingerprints(b.column(1), PRINT_SHINGLE).view(np.int64))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.concatenate(content).view(np.int64)), lists, pa.array(marks, pa.binary()), fp], names=["doc_id", "content", "bands", "marks", "fp"])
        give_back()

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("binary")).mapInArrow(run, "doc_id bigint, content bigint, bands array<bigint>, marks binary, fp bigint")


def shingle_sets(docs: DataFrame, words: int = SHINGLE) -> DataFrame:
    """doc_id, the sorted distinct shingle hashes of the text, as little-endian binary, and its fingerprint fp."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for start, to, data, offsets in blocks(b.column(1)):
                w = Words(data, offsets)
                h, at = shingle_hashes(w.hashes(), w.first, words)
                sets = [np.unique(h[x:y]).tobytes() for x, y in zip(at[:-1], at[1:])]
                fp = pa.array(text_fingerprints(b.column(1).slice(start, to - start), PRINT_SHINGLE).view(np.int64))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(start, to - start), pa.array(sets, pa.binary()), fp], names=["doc_id", "shingles", "fp"])
        give_back()

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("binary")).mapInArrow(run, "doc_id bigint, shingles binary, fp bigint")


_QUOTA = LIMIT * np.arange(1, SEGMENTS + 1) // SEGMENTS


def chain_test(a: np.ndarray, b: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Whether every run of segments of the sketches' rows, read around the ring from ``start``, stays within its share of LIMIT."""
    differ = (a != b).reshape(len(a), SEGMENTS, RUN).sum(axis=2)
    turned = np.take_along_axis(differ, (start[:, None] + np.arange(SEGMENTS)) % SEGMENTS, axis=1)
    return (np.cumsum(turned, axis=1) <= _QUOTA).all(axis=1)


def sketch_forest(ids: np.ndarray, marks: np.ndarray, side: np.ndarray, start: int) -> list[tuple[int, int]]:
    """Edges that span what passes the chain test in one bucket; ``side`` as in simhash.bucket_forest."""
    edges, left = [], np.arange(len(ids))
    while len(left):
        todo, left = [left[0]], left[1:]
        while todo and len(left):
            at = todo.pop()
            far = left[side[left] != side[at]] if side[at] != 2 else left
            hit = far[chain_test(marks[far], marks[[at]], np.full(len(far), start))]
            edges += [(int(ids[at]), int(x)) for x in ids[hit]]
            todo += hit.tolist()
            left = left[~np.isin(left, hit)] if len(hit) else left
    return edges


def sketch_edges(texts: DataFrame, block: int = BLOCK) -> DataFrame:
    """Edges (src, dst) that connect the texts (rep, bands, marks) whose sketches differ in at most LIMIT positions."""
    keyed = texts.select("rep", F.posexplode("bands").alias("band", "key"))
    rows = shared_buckets(keyed, ["band", "key"], "rep", block)
    rows = rows.join(texts.select("rep", "marks"), "rep").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    dealt = rows.select(
        "band", "key", (F.least("own", "other").cast("long") * F.col("parts") + F.greatest("own", "other")).alias("part"),
        F.when(F.col("own") == F.col("other"), 2).when(F.col("own") < F.col("other"), 0).otherwise(1).cast("int").alias("side"), "rep", "marks",
    ).repartition("band", "key", "part").sortWithinPartitions("band", "key", "part")

    def solve(f: pd.DataFrame, begins: np.ndarray) -> Iterator[pd.DataFrame]:
        ids, side, band = f["rep"].to_numpy(), f["side"].to_numpy(), f["band"].to_numpy()
        marks = np.frombuffer(b"".join(f["marks"]), np.uint16).reshape(len(f), SEGMENTS * RUN)
        size = np.diff(np.append(begins, len(f)))
        end, small = np.repeat(begins + size, size), np.repeat(size <= 8, size)
        found = []
        for lag in range(1, 8):  # small buckets, one distance of rows at a time over all of them
            n = max(len(f) - lag, 0)
            at = np.flatnonzero(small[:n] & (np.arange(n) + lag < end[:n]))
            if not len(at):
                break
            at = at[chain_test(marks[at], marks[at + lag], band[at]) & ((side[at] != side[at + lag]) | (side[at] == 2))]
            found.append(np.stack([ids[at], ids[at + lag]], axis=1))
        for a, n in zip(begins[size > 8].tolist(), size[size > 8].tolist()):
            found.append(np.array(sketch_forest(ids[a : a + n], marks[a : a + n], side[a : a + n], int(band[a])), np.int64).reshape(-1, 2))
        if found:
            e = np.unique(np.sort(np.concatenate(found), axis=1), axis=0)
            yield pd.DataFrame({"src": e[:, 0], "dst": e[:, 1]})

    return dealt.mapInPandas(lambda frames: by_group(frames, ["band", "key", "part"], solve), "src bigint, dst bigint").distinct()


def fingerprint_edges(texts: DataFrame, bits: int = BITS) -> DataFrame:
    """Edges (src, dst) that connect the texts (rep, fp) whose fingerprints differ in at most ``bits`` (3 or fewer) bits."""
    prints = stored(texts.groupBy("fp").agg(F.min("rep").alias("low"), F.count("*").alias("n")), "prints")
    shared = checked_small(prints.where("n > 1").select("fp", "low"), "shared-prints")
    equal = texts.join(shared, "fp").where("rep <> low").select(F.col("low").alias("src"), F.col("rep").alias("dst"))
    near = stored(near_edges(prints.select("fp"), bits), "print-edges")
    ends = near.select(F.explode(F.array("src", "dst")).alias("fp")).distinct()
    low = checked_small(prints.join(ends, "fp", "left_semi").select("fp", "low"), "print-ends", 1_000_000)
    for end in ("src", "dst"):  # from fingerprints to texts
        near = near.join(low, near[end] == low["fp"]).drop("fp", end).withColumnRenamed("low", end)
    return equal.unionByName(near)


def by_group(frames: Iterator[pd.DataFrame], keys: list[str], solve) -> Iterator[pd.DataFrame]:
    """``solve(rows, where groups begin)`` over rows sorted by ``keys``; a group that goes on in the next frame waits for it."""
    carry = None
    for f in frames:
        f = f if carry is None else pd.concat([carry, f], ignore_index=True)
        new = np.ones(len(f), bool)
        if len(f):
            new[1:] = np.any([f[k].to_numpy()[1:] != f[k].to_numpy()[:-1] for k in keys], axis=0)
        at = np.flatnonzero(new)
        if len(at) > 1:
            yield from solve(f.iloc[: at[-1]], at[:-1])
        carry = f.iloc[at[-1] :].reset_index(drop=True) if len(at) else f
    if carry is not None and len(carry):
        yield from solve(carry, np.array([0]))


def cluster_forest(ids: np.ndarray, sets: list[np.ndarray], fp: np.ndarray, side: np.ndarray, least: float, bits: int | None) -> list[tuple[int, int]]:
    """Spanning edges of the links of one cluster: a Jaccard similarity of at least ``least`` or, unless ``bits`` is None, a common
    shingle and fingerprints that differ in at most that many bits; ``side`` as in simhash.bucket_forest.
    """
    size = np.array([len(s) for s in sets])
    flat = np.concatenate(sets)
    values, dense = np.unique(flat, return_inverse=True)
    begins = np.concatenate([[0], np.cumsum(size)[:-1]])
    mark = np.zeros(len(values), np.int32)
    left, edges = np.ones(len(ids), bool), []
    for seed in range(len(ids)):
        if not left[seed]:
            continue
        left[seed] = False
        todo = [seed]
        while todo and left.any():
            at = todo.pop()
            own = dense[begins[at] : begins[at] + size[at]]
            mark[own] = 1
            both = np.add.reduceat(mark[dense], begins)
            mark[own] = 0
            hit = both >= least * (size + size[at] - both) - 1e-9
            if bits is not None:
                hit |= (both > 0) & (np.bitwise_count(fp ^ fp[at]) <= bits)
            hit &= left
            if side[at] != 2:
                hit &= side != side[at]
            hit = np.flatnonzero(hit)
            edges += [(int(ids[at]), int(ids[x])) for x in hit]
            left[hit] = False
            todo += hit.tolist()
    return edges


def near_components(docs: DataFrame, words: int = SHINGLE, similarity: float = SIMILARITY, block: int = BLOCK, bits: int | None = None) -> DataFrame:
    """doc_id, component_id for each row that is like another one; every other row is alone.

    Links: equal word sequences, or a Jaccard similarity of the ``words``-word shingle sets of at least
    ``similarity``; with ``bits`` (3 or fewer; :func:`keep_one` has ``BITS``) also SimHash fingerprints that differ in
    at most that many bits, between texts with a common shingle. component_id is the smallest doc_id reachable. Texts without words are equal to one another.
    Null ids are left out; an empty table gives an empty result.
    """
    sketch = stored(with_sketch(docs, words).where("doc_id is not null"), "sketch")
    texts = stored(sketch.groupBy("content").agg(
        F.min("doc_id").alias("rep"), F.first("bands").alias("bands"), F.first("marks").alias("marks"), F.first("fp").alias("fp"), F.count("*").alias("copies")
    ), "texts")
    found = sketch_edges(texts, block)
    if bits is not None:  # texts without words are one text
        found = fingerprint_edges(texts.where(F.size("bands") > 0).select("rep", "fp"), bits).unionByName(found)
    coarse = stored(connected_components(found), "coarse")
    size = coarse.groupBy("component").agg(F.ceil(F.count("*") / F.lit(block)).cast("int").alias("parts"))
    cut = checked_small(size.where("parts > 1"), "cut-clusters")  # the others are one part
    members = coarse.join(cut, "component", "left").select(F.col("node").alias("doc_id"), "component", F.coalesce("parts", F.lit(1)).alias("parts"))
    sets = shingle_sets(docs.join(_ids(members), "doc_id", "left_semi"), words).join(members, "doc_id")
    sets = stored(sets.dropDuplicates(["doc_id"]), "sets")
    own = F.pmod(F.xxhash64("doc_id"), F.col("parts")).cast("int")
    dealt = sets.select("*", own.alias("own"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("other")).select(
        "component", (F.least("own", "other").cast("long") * F.col("parts") + F.greatest("own", "other")).alias("part"),
        F.when(F.col("own") == F.col("other"), 2).when(F.col("own") < F.col("other"), 0).otherwise(1).cast("int").alias("side"), "doc_id", "shingles", "fp",
    )

    def solve(f: pd.DataFrame, begins: np.ndarray) -> Iterator[pd.DataFrame]:
        ids, side, raw, fp = f["doc_id"].to_numpy(), f["side"].to_numpy(), f["shingles"].to_numpy(), f["fp"].to_numpy().view(np.uint64)
        edges = []
        for a, z in zip(begins, np.append(begins[1:], len(f))):
            if z - a > 1:
                edges += cluster_forest(ids[a:z], [np.frombuffer(x, np.uint64) for x in raw[a:z]], fp[a:z], side[a:z], similarity, bits)
        if edges:
            e = np.array(edges, np.int64)
            yield pd.DataFrame({"src": e[:, 0], "dst": e[:, 1]})

    edges = dealt.repartition("component", "part").sortWithinPartitions("component", "part").mapInPandas(lambda frames: by_group(frames, ["component", "part"], solve), "src bigint, dst bigint").distinct()
    parts = connected_components(edges)
    grouped = texts.join(parts, F.col("rep") == F.col("node"), "left").where("copies > 1 or node is not null")
    grouped = grouped.select("content", F.coalesce("component", "rep").alias("component_id"))
    return sketch.join(grouped, "content").select("doc_id", "component_id")


def _ids(members: DataFrame) -> DataFrame:
    return checked_small(members.select("doc_id"), "members", 2_000_000)


def keep_one(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` but those that are like one of a smaller doc_id (repeated rows of one id: all stay or go)."""
    parts = near_components(docs, bits=BITS)
    gone = parts.where("doc_id <> component_id").select(F.col("doc_id").alias("_gone")).distinct()
    gone = checked_small(gone, "gone", 2_000_000)
    return docs.join(gone, docs["doc_id"].cast("bigint") == gone["_gone"], "left_anti")
