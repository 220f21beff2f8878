"""Scoring with a class-based log-bilinear language model, trained in NumPy by noise-contrastive estimation.

Symbols: the most frequent words, END (which also precedes a text), classes of the other head words and RARE.
The model predicts a symbol from the two before it: r = C1*q(s1) + C2*q(s2), score(s) = r.q(s) + b(s), and
P(word | two words before) = softmax over symbols * P(word | symbol), the latter from smoothed counts
(unknown words share as much of RARE as words that stand once). The sum over all training words and one
unknown word is 1.

Word classes come from random indexing: every word adds up the sign vectors of the texts it stands in, which
tells languages and styles apart; the mean vectors are clustered. All counts, vectors and symbol trigrams are taken over
all training rows; the trigram table (at most SYMBOLS**3 rows) is a sufficient statistic for training.
All of them are sums of whole numbers and are put in order before use, so the model is the same in any partitioning.
Words outside the head are looked up by an exchange on their hash, so what is broadcast does not grow.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stseq.llm.common import stored
from stseq.llm.textblock import Lookup, Words, blocks, mix

#: Single-word symbols, word classes, head words (bound of the broadcast) and their least count, dimensions of sign vectors and of the model.
SINGLES, CLASSES, HEAD, LEAST_COUNT, SIGNS, WIDTH = 62, 64, 1 << 18, 3, 4, 32
SYMBOLS = SINGLES + CLASSES + 2
END, RARE = 0, SYMBOLS - 1
NOISE, STEPS, BATCH, RATE = 12, 3000, 2048, 0.02
_END_HASH = np.uint64(1)
_COUNT_TOKENS = 1 << 21
#: Parts of one in which sign vectors are counted.
FIXED = 1 << 16


def held_out(id_col: str = "doc_id", folds: int = 5, fold: int = 1):
    """crc32(id as text) mod ``folds`` is ``fold``; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % folds == fold


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def count_words(train: DataFrame) -> DataFrame:
    """h (word hash), n, v0.. (sums of sign vectors) over the rows of ``train`` (a binary column)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0

        def flush():
            h = np.concatenate([x[0] for x in held])
            v = np.concatenate([x[1] for x in held])
            n = np.concatenate([x[2] for x in held])
            order = np.argsort(h, kind="stable")
            h, v, n = h[order], v[order], n[order]
            new = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
            return h[new], np.add.reduceat(v, new), np.add.reduceat(n, new)

        for b in batches:
            for _, _, data, offsets in blocks(b.column(0)):
                w = Words(data, offsets)
                h = w.hashes()
                text = w.texts()
                bits = mix(h)
                per = np.maximum(np.diff(w.first), 1)
                v = np.empty((len(h), SIGNS), np.int64)
                for d in range(SIGNS):
                    sign = ((bits >> np.uint64(d)) & np.uint64(1)).astype(np.float64) * 2 - 1
                    # whole numbers, so that the sums do not depend on the order of the rows
                    v[:, d] = (np.bincount(text, sign, len(per)) * FIXED // per)[text]
                held.append((np.append(h, _END_HASH), np.append(v, np.zeros((1, SIGNS), np.int64), axis=0), np.append(np.ones(len(h), np.int64), len(per))))
                size += len(h) + 1
                if size > _COUNT_TOKENS:
                    held = [flush()]
                    size = len(held[0][0])
                    if size > _COUNT_TOKENS // 2:
                        yield out(held[0])
                        held, size = [], 0
        if held:
            yield out(flush())

    def out(x):
        h, v, n = x
        return pa.RecordBatch.from_arrays([_signed(h), pa.array(n), *(pa.array(v[:, d]) for d in range(SIGNS))], names=["h", "n", *(f"v{d}" for d in range(SIGNS))])

    schema = "h bigint, n bigint, " + ", ".join(f"v{d} bigint" for d in range(SIGNS))
    sums = [F.sum("n").alias("n"), *[F.sum(f"v{d}").alias(f"v{d}") for d in range(SIGNS)]]
    return train.mapInArrow(run, schema).groupBy("h").agg(*sums)


def cluster(points: np.ndarray, weights: np.ndarray, k: int, rounds: int = 15, seed: int = 7) -> np.ndarray:
    """k-means labels; the centres start at points drawn by weight and are fitted on all points."""
    if not len(points):
        return np.zeros(0, np.int64)
    rng = np.random.default_rng(seed)
    some = rng.choice(len(points), min(len(points), 20_000), replace=False, p=weights / weights.sum()) if len(points) > k else np.arange(len(points))
    centres = points[some[rng.permutation(len(some))[:k]]].copy()
    for _ in range(rounds):
        label = _labels(points, centres)
        n = np.bincount(label, minlength=len(centres))
        for d in range(points.shape[1]):
            total = np.bincount(label, points[:, d], len(centres))
            centres[n > 0, d] = (total / np.maximum(n, 1))[n > 0]
    return _labels(points, centres)


def _labels(points: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return np.concatenate([_nearest(points[a : a + 8192], centres) for a in range(0, len(points), 8192)])


def _nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return np.argmin((centres**2).sum(1) - 2 * x @ centres.T, axis=1)


def most_frequent(words: DataFrame, most: int = HEAD, least: int = LEAST_COUNT) -> tuple[DataFrame, int]:
    """The words of at least ``least`` counts and above a count that at most ``most`` words reach, and how many words stand once.

    Found from a histogram of counts (64 bins a doubling). Rarer words are RARE, so that its mass tells what new texts bring.
    """
    level = F.floor(F.log2(F.col("n").cast("double")) * 64)
    bins = words.groupBy(level.alias("level")).count().orderBy(F.desc("level")).collect()
    total, cut = 0, math.floor(math.log2(least) * 64)
    for r in bins:
        total += r["count"]
        if total > most:
            cut = max(cut, r["level"] + 1)
            break
    return words.where((level >= cut) & (F.col("n") >= least)), sum(r["count"] for r in bins if r["level"] == 0)


def head_symbols(head: pa.Table) -> dict:
    """Symbols of the head words from their counts and vectors (columns h, n, v..); sorted by hash."""
    h = head["h"].to_numpy().astype(np.int64).view(np.uint64)
    n = head["n"].to_numpy().astype(np.float64)
    v = np.stack([head[f"v{d}"].to_numpy().astype(np.float64) for d in range(SIGNS)], axis=1) / FIXED
    symbol = np.full(len(h), RARE, np.int64)
    by_count = np.lexsort((h, -n))
    symbol[by_count[:SINGLES]] = 1 + np.arange(min(SINGLES, len(h)))
    rest = by_count[SINGLES:]
    mean = v[rest] / np.maximum(n[rest], 1)[:, None]
    # few texts tell little: shrink to the middle, and let frequency part classes as well
    mean = mean * (n[rest] / (n[rest] + 3))[:, None]
    if len(rest):
        mean = mean / (mean.std(axis=0) + 1e-9)
        mean = np.concatenate([mean, 0.3 * np.log(n[rest])[:, None]], axis=1)
    symbol[rest] = 1 + SINGLES + cluster(mean, np.sqrt(n[rest]), CLASSES)
    order = np.argsort(h)
    return {"keys": h[order], "symbol": symbol[order].astype(np.int16), "n": n[order]}


def count_trigrams(train: DataFrame, head: dict) -> DataFrame:
    """Counts of symbol trigrams (s1*S*S + s2*S + s3) over all training rows."""
    shared = train.sparkSession.sparkContext.broadcast(head)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        find = Lookup(shared.value["keys"])
        total = np.zeros(SYMBOLS**3, np.int64)
        for b in batches:
            for _, _, data, offsets in blocks(b.column(0)):
                seq, _, first = symbol_sequence(Words(data, offsets), find, shared.value["symbol"])
                code = (seq[:-2] * SYMBOLS + seq[1:-1]) * SYMBOLS + seq[2:]
                ends_in = np.ones(len(seq), bool)  # words and closing ENDs; the two ENDs before a text are context only
                ends_in[first], ends_in[first + 1] = False, False
                total += np.bincount(code[ends_in[2:]], minlength=SYMBOLS**3)
        at = np.flatnonzero(total)
        for a in range(0, len(at), 100_000):
            part = at[a : a + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(total[part])], names=["code", "n"])

    return train.mapInArrow(run, "code bigint, n bigint").groupBy("code").agg(F.sum("n").alias("n"))


def symbol_sequence(w: Words, find: Lookup, symbols: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Symbols of all texts, each as END END w.. END; each word's position in the head (-1: none); where each text begins."""
    n = np.diff(w.first)
    at = find(w.hashes())
    seq = np.zeros(len(at) + 3 * len(n), np.int64)
    seq[np.arange(len(at)) + 3 * w.texts() + 2] = np.where(at >= 0, symbols[np.maximum(at, 0)] if len(symbols) else RARE, RARE)
    return seq, at, w.first[:-1] + 3 * np.arange(len(n))


def train_lbl(code: np.ndarray, count: np.ndarray, seed: int = 11, steps: int = STEPS) -> dict:
    """Noise-contrastive training on weighted trigrams: minibatches from their empirical distribution, unigram noise, Adam."""
    rng = np.random.default_rng(seed)
    s3 = code % SYMBOLS
    s2, s1 = (code // SYMBOLS) % SYMBOLS, code // SYMBOLS**2
    unigram = np.bincount(s3, count, SYMBOLS)
    noise = (unigram + 1e-3) / (unigram.sum() + 1e-3 * SYMBOLS)
    lognoise = np.log(noise * NOISE)
    p = {
        "q": rng.normal(0, 0.1, (SYMBOLS, WIDTH)), "r": rng.normal(0, 0.1, (SYMBOLS, WIDTH)),
        "c1": np.eye(WIDTH) * 0.3, "c2": np.eye(WIDTH) * 0.7, "b": np.log(noise),
    }
    m = {k: np.zeros_like(x) for k, x in p.items()}
    v = {k: np.zeros_like(x) for k, x in p.items()}
    total = np.cumsum(count, dtype=np.float64)
    noise_at = np.cumsum(noise)
    for step in range(1, steps + 1):
        pick = np.minimum(np.searchsorted(total, rng.random(BATCH) * total[-1], "right"), len(code) - 1)
        a, b = s1[pick], s2[pick]
        target = np.concatenate([s3[pick][:, None], np.minimum(np.searchsorted(noise_at, rng.random((BATCH, NOISE))), SYMBOLS - 1)], axis=1)
        ra, rb = p["r"][a], p["r"][b]
        ctx = ra @ p["c1"] + rb @ p["c2"]
        qt = p["q"][target]
        delta = np.einsum("bd,bkd->bk", ctx, qt) + p["b"][target] - lognoise[target]
        err = 1 / (1 + np.exp(-np.clip(delta, -30, 30)))
        err[:, 0] -= 1
        err /= BATCH
        g = {k: np.zeros_like(x) for k, x in p.items()}
        # gradients as matrix products over a one-hot table of symbols
        hot = np.zeros((BATCH, SYMBOLS))
        np.add.at(hot, (np.arange(BATCH)[:, None], target), err)
        g["q"] = hot.T @ ctx
        g["b"] = hot.sum(0)
        gctx = hot @ p["q"]
        g["c1"], g["c2"] = ra.T @ gctx, rb.T @ gctx
        one = np.zeros((BATCH, SYMBOLS))
        one[np.arange(BATCH), a] = 1
        two = np.zeros((BATCH, SYMBOLS))
        two[np.arange(BATCH), b] = 1
        g["r"] = one.T @ (gctx @ p["c1"].T) + two.T @ (gctx @ p["c2"].T)
        rate = RATE * min(1.0, 2 * (1 - step / (steps + 1)))
        for k in p:
            m[k] = 0.9 * m[k] + 0.1 * g[k]
            v[k] = 0.999 * v[k] + 0.001 * g[k] ** 2
            p[k] -= rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
    return p


def log_table(p: dict) -> np.ndarray:
    """log10 P(s3 | s1, s2) for all contexts: batched matrix products and an exact softmax."""
    left, right = p["r"] @ p["c1"], p["r"] @ p["c2"]
    out = np.empty((SYMBOLS, SYMBOLS, SYMBOLS), np.float32)
    for a in range(SYMBOLS):
        score = (left[a] + right) @ p["q"].T + p["b"]
        score -= score.max(axis=1, keepdims=True)
        out[a] = (score - np.log(np.exp(score).sum(axis=1, keepdims=True))) / math.log(10)
    return out


def train_model(train: DataFrame) -> tuple[dict, DataFrame]:
    """The model's arrays (bounded) and the stored counts of all training words (h, n)."""
    counts = stored(count_words(train), "word-counts")
    words = counts.where(F.col("h") != int(_END_HASH))
    t = counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("tokens"), F.count("*").alias("v")).first()
    frequent, once = most_frequent(words)
    head = head_symbols(frequent.toArrow())
    rows = count_trigrams(train, head).toArrow()
    code, n = rows["code"].to_numpy().astype(np.int64), rows["n"].to_numpy().astype(np.float64)
    order = np.argsort(code)  # the draws of the training go by place, whatever order the rows came in
    code, n = code[order], n[order]
    tokens, v = int(t["tokens"]), int(t["v"])
    model = {"keys": head["keys"], "symbol": head["symbol"], "n": head["n"], "tokens": tokens, "v": v}
    ends = tokens - int(_words_total(words))
    model["ends"] = ends
    if len(code):
        table = log_table(train_lbl(code, n))
    else:
        table = np.full((SYMBOLS,) * 3, -math.log10(SYMBOLS), np.float32)
    model["table"] = table
    # P(word | symbol): counts of the symbol's words, smoothed; RARE also has the unknown word
    size = np.bincount(head["symbol"], minlength=SYMBOLS).astype(float)
    mass = np.bincount(head["symbol"], head["n"], SYMBOLS)
    known_rare = v - (1 if ends else 0) - len(head["keys"])
    model["rare_mass"], model["rare_size"] = tokens - ends - float(head["n"].sum()), known_rare
    # share of RARE for unknown words: how often training words were new (words that stand once)
    model["unknown"] = min(0.95, (once + 0.5) / (model["rare_mass"] + 1)) if known_rare else 1.0
    within = (head["n"] + 0.5) / (mass[head["symbol"]] + 0.5 * size[head["symbol"]]) if len(head["n"]) else np.zeros(0)
    model["within"] = np.log10(within)
    model["base"] = np.log10((head["n"] + 0.5) / (tokens + 0.5 * (v + 1)))
    model["end_base"] = math.log10((ends + 0.5) / (tokens + 0.5 * (v + 1)))
    return model, counts


def _words_total(words: DataFrame) -> int:
    return words.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]


def score_texts(docs: DataFrame, train_where=None, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row; log10 probabilities of whole texts.

    The model learns from the rows that are not held out. Null and empty texts have one token, the end. Repeated
    rows stay. With no training rows every word is unknown and the symbols are equally likely.
    """
    out_of = held_out(id_col) if train_where is None else ~train_where
    marked = docs.select(F.col(id_col), out_of.alias("held_out"), F.col(text).cast("binary").alias("text"))
    model, counts = train_model(marked.where("not held_out").select("text"))
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        find, table = Lookup(m["keys"]), m["table"].reshape(-1)
        for b in batches:
            for start, to, data, offsets in blocks(b.column(2)):
                w = Words(data, offsets)
                seq, at, first = symbol_sequence(w, find, m["symbol"])
                n = np.diff(w.first)
                logp = np.zeros(len(seq))
                logp[2:] = table[(seq[:-2] * SYMBOLS + seq[1:-1]) * SYMBOLS + seq[2:]]
                logp[first], logp[first + 1] = 0, 0  # the two ENDs before a text
                total = np.concatenate([[0], np.cumsum(logp)])
                score = total[first + n + 3] - total[first]
                known = at >= 0
                inside = np.concatenate([[0], np.cumsum(np.where(known, m["within"][np.maximum(at, 0)] if len(m["within"]) else 0, 0))])
                base = np.concatenate([[0], np.cumsum(np.where(known, m["base"][np.maximum(at, 0)] if len(m["base"]) else 0, 0))])
                hits = np.concatenate([[0], np.cumsum(known)])
                a, z = w.first[:-1], w.first[1:]
                rare = w.hashes()[~known]
                rare_at = np.concatenate([[0], np.cumsum(~known)])[w.first]
                yield pa.RecordBatch.from_arrays(
                    [
                        b.column(0).slice(start, to - start), b.column(1).slice(start, to - start), pa.array(n + 1),
                        pa.array(hits[z] - hits[a] + (1 if m["ends"] else 0)), pa.array(base[z] - base[a] + m["end_base"]),
                        pa.array(score + inside[z] - inside[a]), pa.ListArray.from_arrays(pa.array(rare_at.astype(np.int32)), _signed(rare)),
                    ],
                    names=[id_col, "held_out", "n_tokens", "n_known", "base_score", "score", "rare"],
                )

    scored = marked.mapInArrow(run, f"{id_col} {kind}, held_out boolean, n_tokens bigint, n_known bigint, base_score double, score double, rare array<bigint>")
    scored = stored(scored.withColumn("_row", F.monotonically_increasing_id()), "scored")
    # words outside the head: their counts by an exchange on the hash, then sums back to the rows
    base_of = F.lit(float(model["tokens"]) + 0.5 * (model["v"] + 1))
    c = F.coalesce(F.col("n"), F.lit(0)) + 0.5
    rare_p = F.when(F.col("n") > 0, c * F.lit((1 - model["unknown"]) / (model["rare_mass"] + 0.5 * model["rare_size"] + 1e-300))).otherwise(F.lit(model["unknown"]))
    tail = scored.select("_row", F.explode("rare").alias("h")).join(counts.select("h", "n"), "h", "left")
    sums = tail.groupBy("_row").agg(
        F.sum(F.when(F.col("n") > 0, 1).otherwise(0)).alias("_known"), F.sum(F.log10(c / base_of)).alias("_base"), F.sum(F.log10(rare_p)).alias("_score")
    )
    return scored.join(sums, "_row", "left").select(
        id_col, "held_out", "n_tokens", (F.col("n_known") + F.coalesce("_known", F.lit(0))).cast("long").alias("n_known"),
        F.lit(model["tokens"]).cast("long").alias("train_tokens"),
        (F.col("base_score") + F.coalesce("_base", F.lit(0.0))).alias("base_score"), (F.col("score") + F.coalesce("_score", F.lit(0.0))).alias("score"),
    )
