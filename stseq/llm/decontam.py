"""Benchmark decontamination by pigeonhole edit matching.

Texts are compared as lower-case letters and digits of any script, everything else being one space; lengths and edits
count characters. An item of n characters may differ from a passage in up to e = floor(n * ``BUDGET``) edits. Cut into
e+1 pieces, at least one piece stands in the passage unchanged. One automaton over all pieces finds the exact
hits in each whole text; around a hit Myers' bit-parallel scan gives the least edit distance between the item
and any substring, and the item is found if that is at most e. Items below ``SHORTEST`` characters are found exactly, between word borders.

The benchmark is broadcast to the tasks in runs of a bounded size; a larger one takes more passes over the texts.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stseq.llm.common import checked_small

#: Edits allowed, as a share of an item's length, and the shortest item (normalised characters) that may differ at all.
BUDGET, SHORTEST = 0.05, 40
#: Bytes of benchmark text that may be broadcast at once.
BROADCAST_BYTES = 64 << 20
_CLEAN = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


_ODD = re.compile(r"[\W_]+")


def normalise(text: str) -> str:
    """Lower-case letters and digits of any script; all else is single spaces."""
    if text.isascii():
        return b" ".join(text.encode().translate(_CLEAN).split()).decode()
    return _ODD.sub(" ", text.lower()).strip()


def myers(pattern: str, text: str, limit: int) -> tuple[int, int] | None:
    """Least edit distance between ``pattern`` and a substring of ``text``, and where the first such one ends; None above ``limit``."""
    m = len(pattern)
    if not m:
        return (0, 0)
    masks: dict[str, int] = {}
    for i, c in enumerate(pattern):
        masks[c] = masks.get(c, 0) | (1 << i)
    full, high = (1 << m) - 1, 1 << (m - 1)
    plus, minus, score = full, 0, m
    best, end = m + 1, 0
    for j, c in enumerate(text):
        eq = masks.get(c, 0)
        vertical = eq | minus
        diagonal = (((eq & plus) + plus) ^ plus) | eq
        up = minus | (full & ~(diagonal | plus))
        down = plus & diagonal
        if up & high:
            score += 1
        elif down & high:
            score -= 1
        up = (up << 1) & full
        down = (down << 1) & full
        plus = down | (full & ~(vertical | up))
        minus = up & vertical
        if score < best:
            best, end = score, j + 1
    return (best, end) if best <= limit else None


class Items:
    """The automaton over the pieces of all items."""

    def __init__(self, items: list[tuple[int, str]], budget: float = BUDGET, shortest: int = SHORTEST):
        self.items = [(i, t, int(len(t) * budget) if len(t) >= shortest else 0) for i, t in items if t]
        self.shortest = shortest
        where: dict[str, list[tuple[int, int]]] = {}
        for k, (_, t, e) in enumerate(self.items):
            cuts = np.linspace(0, len(t), e + 2).astype(int)
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
                where.setdefault(t[a:b], []).append((k, a))
        self.automaton = None
        if where:
            import ahocorasick

            self.automaton = ahocorasick.Automaton()
            for piece, at in where.items():
                self.automaton.add_word(piece, (len(piece), at))
            self.automaton.make_automaton()

    def find(self, text: str) -> list[tuple[int, int, int, int]]:
        """(item_id, distance, start of the window, end of the match) of each item found in a normalised text."""
        if self.automaton is None or not text:
            return []
        spots: dict[int, set[int]] = {}
        for end, (n, at) in self.automaton.iter(text):
            for k, a in at:
                m = len(self.items[k][1])
                if m < self.shortest:  # one exact copy between word borders will do
                    s = end + 1 - m
                    if k in spots or text[max(0, s - 1) : s].strip() or text[end + 1 : end + 2].strip():
                        continue
                spots.setdefault(k, set()).add(end + 1 - n - a)
        out = []
        for k, begins in spots.items():
            item, t, e = self.items[k]
            best, reach = None, -1
            run: list[list[int]] = []
            for s in sorted(begins):  # windows that overlap are scanned as one
                a, b = max(0, s - e), min(len(text), s + len(t) + e)
                if run and a <= reach:
                    run[-1][1] = b
                else:
                    run.append([a, b])
                reach = b
            for a, b in run:
                whole = text.find(t, a, b)
                got = (0, whole + len(t) - a) if whole >= 0 else myers(t, text[a:b], e)
                if got and (best is None or got[0] < best[1]):
                    best = (item, got[0], max(0, a + got[1] - len(t)), a + got[1])
                if best and best[1] == 0:
                    break
            if best:
                out.append(best)
        return out


def benchmark_runs(benchmark: DataFrame, limit: int = BROADCAST_BYTES) -> list[list[tuple[int, str]]]:
    """Normalised items in runs of about ``limit`` bytes at most; rows with a null are left out."""
    rows = benchmark.where("text is not null and item_id is not null").select("item_id", "text").distinct()
    size = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    n = max(1, -(-2 * size // limit)) if size > limit else 1  # dealt by a hash, so half full
    runs = (rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k).collect() for k in range(n))
    return [sorted((r["item_id"], normalise(r["text"])) for r in run) for run in runs]


def contaminated(docs: DataFrame, benchmark: DataFrame, budget: float = BUDGET, shortest: int = SHORTEST, limit: int = BROADCAST_BYTES) -> DataFrame:
    """doc_id, item_id, distance, match_start, match_end for each item found in each row.

    Positions are characters of the normalised text. Items shorter than ``shortest`` characters are looked for exactly, as whole
    words; a null or empty text holds none; repeated rows are reported each.
    """
    kind = docs.schema["doc_id"].dataType.simpleString()
    texts = docs.select("doc_id", "text")

    def one(shared) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            items = Items(shared.value, budget, shortest)
            for b in batches:
                ids, found = [], []
                for i in range(b.num_rows):
                    for hit in items.find(normalise(b.column(1)[i].as_py() or "")):
                        ids.append(b.column(0)[i].as_py())
                        found.append(hit)
                cols = list(zip(*found)) if found else [[], [], [], []]
                yield pa.RecordBatch.from_arrays([pa.array(ids, b.schema.field(0).type), *(pa.array(c, pa.int64()) for c in cols)], names=["doc_id", "item_id", "distance", "match_start", "match_end"])

        return texts.mapInArrow(run, f"doc_id {kind}, item_id bigint, distance bigint, match_start bigint, match_end bigint")

    return reduce(DataFrame.unionByName, [one(docs.sparkSession.sparkContext.broadcast(items)) for items in benchmark_runs(benchmark, limit)])


def remove_contaminated(docs: DataFrame, benchmark: DataFrame, limit: int = BROADCAST_BYTES) -> DataFrame:
    """The rows whose text holds no item; the columns of ``docs``.

    Only the hits are stored, by doc_id and a hash of the text; the rows themselves never pass through Python. Null and
    empty texts stay; repeated rows stay or go together, and rows of one id but other texts are judged each.
    """
    keyed = docs.select(F.struct("doc_id", F.xxhash64("text").alias("mark")).alias("doc_id"), "text")
    hits = contaminated(keyed, benchmark, limit=limit).select(F.col("doc_id.doc_id").alias("_id"), F.col("doc_id.mark").alias("_mark")).distinct()
    gone = checked_small(hits, "contaminated")
    return docs.join(gone, docs["doc_id"].eqNullSafe(gone["_id"]) & (F.xxhash64(docs["text"]) == gone["_mark"]), "left_anti")
