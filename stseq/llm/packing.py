"""Packing token pieces into training sequences of equal attention cost.

A piece of n tokens costs ``LINEAR*n + QUADRATIC*n*n`` (projections, and attention within the piece). Documents
are cut into whole sequences and one remainder. Remainders are packed in groups of about ``GROUP_SEQUENCES``
sequences: in descending order each goes to the sequence of lowest cost that still has room. One remainder in
``FILLERS`` (by a hash) comes after the others and is cut wherever that fills a sequence; only these carry their
ids through the exchange, the others just a checksum. Groups are dealt by a hash, so their number grows with
the input and no group does.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stseq.llm.common import stored
from stseq.llm.textblock import Lookup, Words, blocks, give_back

CAPACITY, END_ID = 2048, 1
LINEAR, QUADRATIC = 1.0, 1.0 / 512
GROUP_SEQUENCES = 512
FILLERS = 8
VOCABULARY = "word_bpe_49k.json"
#: Distinct words whose ids a worker keeps (about 30 bytes each), and bytes of text that it takes at once.
CACHED_WORDS, CHUNK_BYTES = 1_000_000, 4 << 20


def tokenizer_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class Ids:
    """Token ids of texts. This vocabulary lower-cases, and its pre-tokenizer never joins what white space parts, so each word is encoded once and kept.

    Words are known by a 64-bit hash; their ids lie one after another in one array.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        vocabulary = self.tokenizer.get_vocab()
        self.closes = np.zeros(max(vocabulary.values()) + 1, bool)  # ids that end a piece of a word
        self.closes[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True
        self._forget()

    @classmethod
    def shared(cls, path: str) -> Ids:
        """One for the worker process, so that its words outlive a task."""
        if path not in _shared:
            _shared[path] = cls(path)
        return _shared[path]

    def _forget(self) -> None:
        self.keys, self.at, self.size = np.zeros(0, np.uint64), np.zeros(0, np.int32), np.zeros(0, np.int32)
        self.flat, self.find = np.zeros(0, "<u4"), Lookup(np.zeros(0, np.uint64))

    def of(self, text: str) -> np.ndarray:
        return self.of_column(pa.array([text.encode()], pa.binary()))[0]

    def of_column(self, texts: pa.Array) -> list[np.ndarray]:
        """Ids of a binary column of UTF-8 texts (null: none); its unknown words are encoded together."""
        if len(self.keys) > CACHED_WORDS:
            self._forget()
        parts, new, special = [], {}, set()
        for start, _, data, offsets in blocks(texts):
            w = Words(data, offsets)
            h = w.hashes()
            at = self.find(h)
            miss = np.flatnonzero(at < 0)
            if len(miss):
                unique, first = np.unique(h[miss], return_index=True)
                for k, i in zip(unique.tolist(), miss[first].tolist()):
                    if k not in new:
                        new[k] = w.data[w.starts[i] : w.ends[i]].tobytes()
            odd = np.flatnonzero((data[:-1] == 60) & (data[1:] == 124))  # "<|" may begin a special token, which depends on case
            special.update((np.searchsorted(offsets, odd, "right") - 1 + start).tolist())
            parts.append((h, at, miss, w.first))
        if new:
            self._add(np.array(list(new), np.uint64), self._encoded(list(new.values())))
        out: list[np.ndarray] = []
        for h, at, miss, first in parts:
            if new:  # the table was built anew
                at = self.find(h)
            n = self.size[at]
            ends = np.concatenate([[0], np.cumsum(n)])
            ids = self.flat[np.repeat(self.at[at] - ends[:-1], n) + np.arange(ends[-1])]
            edge = ends[first].tolist()
            out += [ids[a:z] for a, z in zip(edge, edge[1:])]
        for i in special:
            out[i] = np.array(self.tokenizer.encode(texts[i].as_py().decode(), add_special_tokens=False).ids, "<u4")
        return out

    def _add(self, keys: np.ndarray, ids: list[np.ndarray]) -> None:
        size = np.array([len(x) for x in ids], np.int32)
        at = (len(self.flat) + np.cumsum(size) - size).astype(np.int32)
        self.flat = np.concatenate([self.flat, *ids]).astype("<u4")
        keys, at, size = np.concatenate([self.keys, keys]), np.concatenate([self.at, at]), np.concatenate([self.size, size])
        order = np.argsort(keys)
        self.keys, self.at, self.size = keys[order], at[order], size[order]
        self.find = Lookup(self.keys)

    def _encoded(self, words: list[bytes]) -> list[np.ndarray]:
        """Ids of each word. Words of letters, with or without ASCII marks after them, go joined by spaces: their pieces (one or
        two) are closed by ids that tell so, and if their number does not add up each word is encoded alone.
        """
        out: list[np.ndarray | None] = [None] * len(words)
        joined, alone = [], []
        for i, w in enumerate(words):
            core = w.rstrip(_MARKS)
            if core.isalpha() or core.decode().isalpha():
                joined.append((i, 1 if len(core) == len(w) else 2))
            else:
                alone.append(i)
        for a in range(0, len(joined), _JOINED):
            part = joined[a : a + _JOINED]
            ids = np.array(self._encode([b" ".join([words[i] for i, _ in part]).decode()])[0].ids, "<u4")
            closed = np.flatnonzero(self.closes[ids]) + 1
            last = np.cumsum([k for _, k in part])
            if last[-1] != len(closed):
                alone += [i for i, _ in part]
                continue
            ends = closed[last - 1].tolist()
            for (i, _), x, y in zip(part, [0, *ends], ends):
                out[i] = ids[x:y]
        for i, e in zip(alone, self._encode([words[i].decode() for i in alone])):
            out[i] = np.array(e.ids, "<u4")
        return out

    def _encode(self, texts: list[str]) -> list:
        return self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)


#: New words that are encoded as one text.
_JOINED = 8192
#: ASCII marks that may end a word, the apostrophe (which may bind) left out.
_MARKS = bytes(c for c in range(33, 127) if not chr(c).isalnum() and c != 39)
_shared: dict[str, Ids] = {}


def cut_pieces(docs: DataFrame, path: str, capacity: int = CAPACITY, end_id: int = END_ID, text: str = "text", fillers: int = FILLERS) -> DataFrame:
    """Whole sequences and remainders of each row: doc_id, start, length, doc_tokens, crc (of the ids), ids.

    ids (binary, little-endian unsigned 32-bit) are there for one remainder in ``fillers``, else null.
    """
    name = docs.schema["doc_id"].dataType.simpleString()
    kind = pa.string() if name == "string" else pa.int64()
    name = name if name == "string" else "bigint"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids_of = Ids.shared(path)
        for b in batches:
            rows = []
            texts = b.column(1)
            found = (ids for start, to, _, _ in blocks(texts, CHUNK_BYTES) for ids in ids_of.of_column(texts.slice(start, to - start)))
            for doc, ids in zip(b.column(0).to_pylist(), found):
                ids = np.append(ids, np.uint32(end_id)).astype("<u4")
                for at in range(0, len(ids), capacity):
                    piece = ids[at : at + capacity].tobytes()
                    crc = zlib.crc32(piece)
                    n = len(piece) // 4
                    rows.append((doc, at, n, len(ids), crc, piece if n < capacity and crc % fillers == 0 else None))
            if rows:
                cols = list(zip(*rows))
                kinds = [kind, pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=["doc_id", "start", "length", "doc_tokens", "crc", "ids"])
        give_back()

    return docs.select(F.col("doc_id").cast(name), F.col(text).cast("binary")).mapInArrow(
        run, f"doc_id {name}, start bigint, length bigint, doc_tokens bigint, crc bigint, ids binary"
    )


def assign(lengths: np.ndarray, filler: np.ndarray, capacity: int = CAPACITY) -> list[tuple[int, int, int, int]]:
    """(piece, from, length, sequence) for pieces below ``capacity`` tokens: descending, lowest cost with room first, fillers last and cut."""
    total = int(lengths.sum())
    n = -(-total // capacity)
    cost, room, out = np.zeros(n), np.full(n, capacity, np.int64), []
    for i in np.lexsort((-lengths, filler)).tolist():
        at, left = 0, int(lengths[i])
        while left:
            open_ = np.where(room >= left, cost, np.inf) if len(room) else np.zeros(0)
            s = int(np.argmin(open_)) if len(room) else 0
            take = left
            if not len(room) or open_[s] == np.inf:
                s = int(np.argmax(room)) if len(room) else 0
                if filler[i] and len(room) and room[s] > 0:
                    take = int(room[s])
                else:  # no room anywhere: one more sequence
                    s = len(room)
                    cost, room = np.append(cost, 0.0), np.append(room, capacity)
            out.append((i, at, take, s))
            room[s] -= take
            cost[s] += LINEAR * take + QUADRATIC * take * take
            at, left = at + take, left - take
    return out


def pack(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """One row a piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    A null text counts as empty and still has its end id; repeated rows are packed each; an empty table gives
    an empty result. Only the last sequences of a group are padded.
    """
    pieces = stored(cut_pieces(docs, path or tokenizer_path(), capacity, end_id), "pieces")
    full = pieces.where(F.col("length") == capacity)
    short = pieces.where(F.col("length") < capacity)
    tokens = short.agg(F.sum("length")).first()[0] or 0
    groups = max(1, -(-tokens // (capacity * GROUP_SEQUENCES)))
    # dealt by a hash of the piece and its place in its task, so that copies of a row spread as well
    key = F.pmod(F.xxhash64("doc_id", "start", F.monotonically_increasing_id()), F.lit(groups)).alias("grp")
    kind = pieces.schema["doc_id"].dataType.simpleString()

    def group(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["doc_id", "start"], kind="stable", ignore_index=True)
        ids, starts, crcs = pdf["ids"].tolist(), pdf["start"].tolist(), pdf["crc"].tolist()
        lengths = pdf["length"].to_numpy(np.int64)
        used: dict[int, int] = {}
        rows = []
        for i, at, take, s in assign(lengths, pdf["ids"].notna().to_numpy(), capacity):
            crc = crcs[i] if take == lengths[i] else zlib.crc32(ids[i][4 * at : 4 * (at + take)])
            rows.append((i, starts[i] + at, take, crc, s, used.get(s, 0)))
            used[s] = used.get(s, 0) + take
        i, start, length, crc, seq, off = zip(*rows)
        i, grp = list(i), int(pdf["grp"].iloc[0])
        return pd.DataFrame({
            "doc_id": pdf["doc_id"].to_numpy()[i], "start": start, "length": length, "ids_crc32": crc, "doc_tokens": pdf["doc_tokens"].to_numpy()[i],
            "sequence_id": 2 * (np.array(seq, np.int64) * groups + grp) + 1, "offset": off,
        })

    packed = short.select("*", key).groupBy("grp").applyInPandas(
        group, f"doc_id {kind}, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint"
    )
    whole = full.select(
        "doc_id", "start", "length", F.col("crc").alias("ids_crc32"), "doc_tokens",
        (2 * F.monotonically_increasing_id()).alias("sequence_id"), F.lit(0).cast("bigint").alias("offset"),
    )
    return whole.unionByName(packed)


def sequences(docs: DataFrame, plan: DataFrame, path: str | None = None) -> DataFrame:
    """The token ids of each packed piece (``plan`` from :func:`pack`, ``doc_id`` unique): plan columns and ``ids``."""
    where = path or tokenizer_path()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids_of = Ids.shared(where)
        for b in batches:
            yield b.assign(ids=[
                np.append(ids_of.of(t or ""), np.uint32(END_ID))[a : a + n].tolist() for t, a, n in zip(b["text"], b["start"], b["length"])
            ]).drop(columns="text")

    joined = plan.join(docs.select("doc_id", "text"), "doc_id")
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in plan.select("*").schema) + ", ids array<bigint>"
    return joined.select(*plan.columns, "text").mapInPandas(run, schema)


def check_crc(ids: list[int]) -> int:
    """CRC-32 of ids as little-endian unsigned 32-bit numbers (for tests)."""
    return zlib.crc32(np.array(ids, "<u4").tobytes())
