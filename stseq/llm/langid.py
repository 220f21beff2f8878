"""Language identification by Bayesian fusion of text, declared language, address suffix and host priors.

log P(l | all) = log P(l | host) + log P(declared | l) + log P(suffix | l) + log P(text | l) + constant.

Text: naive Bayes over hashed words, fitted on a bounded sample of each label's texts; every label is kept. Host priors: counts of each
host's languages as the text alone tells them, shrunk to its registered domain's and that to all rows'
(grouped aggregation). The tables of declarations and suffixes are counted the same way over all rows. Text
evidence is tempered (words of a text are not independent) so that a declaration can decide short texts.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stseq.llm.common import checked_small, stored
from stseq.llm.decontam import _CLEAN
from stseq.llm.textblock import Words, blocks, give_back

#: Distinct texts of each label that the text model is fitted on (expected bound), and languages in one block of its table.
LABEL_ROWS, BLOCK_LANGUAGES = 2_500, 64
#: Languages whose running sums over a block of words are in memory at once.
SUM_LANGUAGES = 16
BUCKET_BITS = 16
#: Weight of each word's evidence, pages that a prior weighs, pseudo-count of the evidence tables.
TEMPER, STRENGTH, PSEUDO = 0.3, 20.0, 1.0
#: A row is rejected ("und") below this posterior, without words, or with hardly a word that the model has seen.
LEAST_POSTERIOR, LEAST_KNOWN, KNOWN_WORDS = 0.5, 0.02, 20
UNDETERMINED = "und"
_TABLE = np.frombuffer(_CLEAN, np.uint8)
_LANG = re.compile(r"<html\b[^>]*?\blang\s*=\s*[\"']?\s*([A-Za-z]{2,3})", re.I)


def fit_text_model(labelled: DataFrame, label_rows: int = LABEL_ROWS, text: str = "text", label: str = "lang") -> dict:
    """Word-bucket log probabilities of each language from a hash sample of about ``label_rows`` distinct texts of each label.

    The text of the smallest hash is always drawn, so no label is lost. ``logp`` is a list of tables of at most
    BLOCK_LANGUAGES languages, in the order of ``langs``.
    """
    rows = labelled.where(F.col(label).isNotNull() & (F.col(label) != "") & F.col(text).isNotNull())
    rows = rows.select(F.col(text).cast("binary").alias("text"), F.col(label).alias("lang"), F.shiftrightunsigned(F.xxhash64(text, label), 2).alias("at"))
    cuts = rows.groupBy("lang").agg(F.min("at").alias("least"), F.approx_count_distinct("at").alias("n"))
    share = F.lit(float(label_rows)) / F.col("n")
    cut = F.when(share >= 1, F.lit(1 << 62)).otherwise(F.greatest("least", (share * F.lit(float(1 << 62))).cast("bigint")))
    cuts = checked_small(cuts.select(F.col("lang").alias("_lang"), cut.alias("cut")), "language-cuts")
    drawn = rows.join(cuts, F.col("lang") == F.col("_lang")).where("at <= cut").dropDuplicates(["lang", "at"])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            langs = b.column(1).to_pylist()
            total: dict[str, np.ndarray] = {}
            for start, _, data, offsets in blocks(b.column(0)):
                w = Words(_TABLE[data], offsets, lower=False)
                bucket = (w.hashes() >> np.uint64(64 - BUCKET_BITS)).astype(np.int64)
                for i in range(len(offsets) - 1):
                    own = bucket[w.first[i] : w.first[i + 1]]
                    have = total.setdefault(langs[start + i], np.zeros(1 << BUCKET_BITS, np.int64))
                    np.add.at(have, own, 1)
            for lang, c in total.items():
                at = np.flatnonzero(c)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at)), pa.array(at, pa.int64()), pa.array(c[at], pa.int64())], names=["lang", "bucket", "n"])

    counted = drawn.select("text", "lang").mapInArrow(count, "lang string, bucket bigint, n bigint")
    counted = stored(counted.groupBy("lang", "bucket").agg(F.sum("n").alias("n")), "language-words")
    langs = sorted(r["lang"] for r in counted.select("lang").distinct().collect())
    tables, seen = [], np.zeros(1 << BUCKET_BITS, bool)
    for lo in range(0, len(langs), BLOCK_LANGUAGES):  # at most 64 languages x 65536 buckets at once
        part = langs[lo : lo + BLOCK_LANGUAGES]
        got = counted.where(F.col("lang").isin(part)).select((F.array_position(F.array(*[F.lit(l) for l in part]), F.col("lang")) - 1).alias("at"), "bucket", "n").toArrow()
        table = np.zeros((1 << BUCKET_BITS, len(part)))
        table[got["bucket"].to_numpy(), got["at"].to_numpy()] = got["n"].to_numpy()
        seen |= table.sum(axis=1) > 0
        tables.append(np.log((table + 0.1) / (table.sum(axis=0) + 0.1 * len(table))).astype(np.float32))
    return {"langs": langs, "logp": tables, "seen": seen}


def with_text_evidence(rows: DataFrame, model: dict, text: str = "text") -> DataFrame:
    """Add ``ll`` (log P(text | l) of each language, tempered), ``n_words`` and ``known`` (share of words seen in fitting).

    One pass over the rows for each block of the model's table, so that a worker holds one block at a time.
    """
    from pyspark.sql.types import ArrayType, DoubleType, LongType, StructType

    at = rows.columns.index(text)
    width = len(rows.columns)
    schema = StructType([*rows.schema.fields]).add("ll", ArrayType(DoubleType())).add("n_words", LongType()).add("known", DoubleType())

    def block_pass(shared, later: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            logp, seen = shared.value
            k = max(logp.shape[1], 1)
            for b in batches:
                ll, n, known = np.zeros((b.num_rows, k)), np.zeros(b.num_rows, np.int64), np.zeros(b.num_rows)
                for start, to, data, offsets in blocks(b.column(at).cast(pa.binary())):
                    w = Words(_TABLE[data], offsets, lower=False)
                    bucket = (w.hashes() >> np.uint64(64 - BUCKET_BITS)).astype(np.int64)
                    n[start:to] = np.diff(w.first)
                    for lo in range(0, logp.shape[1], SUM_LANGUAGES):
                        some = logp[:, lo : lo + SUM_LANGUAGES]
                        total = np.zeros((len(w) + 1, some.shape[1]))
                        np.cumsum(some[bucket], axis=0, dtype=np.float64, out=total[1:])
                        ll[start:to, lo : lo + SUM_LANGUAGES] = (total[w.first[1:]] - total[w.first[:-1]]) * TEMPER
                    hits = np.concatenate([[0], np.cumsum(seen[bucket])])
                    known[start:to] = (hits[w.first[1:]] - hits[w.first[:-1]]) / np.maximum(n[start:to], 1)
                if later:  # behind the languages of the blocks before
                    had = b.column(width)
                    ll = np.hstack([had.flatten().to_numpy().reshape(b.num_rows, -1), ll]) if b.num_rows else ll
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, ll.size + 1, ll.shape[1]), pa.int32()), pa.array(ll.ravel()))
                yield pa.RecordBatch.from_arrays([*b.columns[:width], lists, pa.array(n), pa.array(known)], names=[*b.schema.names[:width], "ll", "n_words", "known"])
            give_back()

        return run

    out = rows
    for i, logp in enumerate(model["logp"] or [np.zeros((1 << BUCKET_BITS, 0), np.float32)]):
        shared = rows.sparkSession.sparkContext.broadcast((logp, model["seen"]))
        out = (stored(out, "evidence-block") if i else out).mapInArrow(block_pass(shared, i > 0), schema)
    return out


def identify(rows: DataFrame, model: dict, text: str = "text", evidence: DataFrame | None = None) -> DataFrame:
    """Add language, posterior and text_language to rows with columns host, domain, suffix, declared (any may be null) and text.

    Rows without words are "und", and so are those below the least posterior or (from 20 words on) with hardly a
    known word. Other columns pass through; repeated rows stay. The intermediate rows are stored once.
    """
    langs = model["langs"]
    if not langs:
        return rows.withColumns({"language": F.lit(UNDETERMINED), "posterior": F.lit(0.0), "text_language": F.lit(UNDETERMINED)})
    scored = stored(with_text_evidence(rows, model, text), "evidence")
    names = F.array(*[F.lit(l) for l in langs])
    best = F.array_position(F.col("ll"), F.array_max("ll"))
    told = scored.withColumn("text_language", F.when(F.col("n_words") > 0, F.element_at(names, best.cast("int"))).otherwise(UNDETERMINED))
    sure = told.where("n_words > 0")
    counts = [F.sum(F.when(F.col("text_language") == l, 1).otherwise(0)).cast("double").alias(f"c{i}") for i, l in enumerate(langs)]
    counts.append(F.count("*").cast("double").alias("cn"))  # each row has one language, so this is their sum
    k = range(len(langs))
    # small tables: one row for all, one a domain, one a host; one a declared value and suffix
    total = sure.agg(*counts).first()
    base = [(float(total[f"c{i}"] or 0) + 1) / (float(total["cn"] or 0) + len(langs)) for i in k]
    grouped = sure.groupBy("domain", "host").agg(*counts)

    def shrunk(prefix: str, priors: list[Column]) -> list[Column]:
        n = F.col(f"{prefix}n")
        return [(F.col(f"{prefix}{i}") + F.lit(STRENGTH) * priors[i]) / (n + F.lit(STRENGTH)) for i in k]

    domains = grouped.groupBy("domain").agg(*[F.sum(f"c{i}").alias(f"d{i}") for i in [*k, "n"]])
    domains = domains.select(F.col("domain").alias("_domain"), *[c.alias(f"p{i}") for i, c in enumerate(shrunk("d", [F.lit(b) for b in base]))])
    hosts = grouped.join(domains, F.col("domain").eqNullSafe(F.col("_domain")))
    hosts = hosts.select(F.col("host").alias("_host"), F.col("domain").alias("_hdomain"), F.array(*[F.log(c) for c in shrunk("c", [F.col(f"p{i}") for i in k])]).alias("_prior"))

    def table(column: str) -> DataFrame:
        """log P(value | l) for each value of a column; null tells nothing."""
        t = sure.where(F.col(column).isNotNull()).groupBy(column).agg(*counts)
        s = t.agg(F.count("*").alias("m"), *[F.sum(f"c{i}").alias(f"s{i}") for i in k]).first()
        size = float(s["m"] or 1)
        logs = [F.log((F.col(f"c{i}") + PSEUDO) / F.lit(float(s[f"s{i}"] or 0) + PSEUDO * size)) for i in k]
        return t.select(F.col(column).alias(f"_{column}"), F.array(*logs).alias(f"_{column}_ll"))

    out = told.join(checked_small(hosts, "hosts"), F.col("host").eqNullSafe(F.col("_host")) & F.col("domain").eqNullSafe(F.col("_hdomain")), "left")
    for column in ("declared", "suffix"):
        t = table(column)
        out = out.join(checked_small(t, column), F.col(column) == F.col(f"_{column}"), "left")
    zero = F.array(*[F.lit(0.0)] * len(langs))
    flat = F.array(*[F.log(F.lit(b)) for b in base])
    score = F.zip_with(F.coalesce("_prior", flat), F.col("ll"), lambda a, b: a + b)
    for column in ("declared", "suffix"):
        score = F.zip_with(score, F.coalesce(F.col(f"_{column}_ll"), zero), lambda a, b: a + b)
    out = out.withColumn("_score", score).withColumn("_top", F.array_max("_score"))
    out = out.withColumn("posterior", 1 / F.aggregate("_score", F.lit(0.0), lambda t, s: t + F.exp(s - F.col("_top"))))
    rejected = (F.col("n_words") == 0) | (F.col("posterior") < LEAST_POSTERIOR) | ((F.col("n_words") >= KNOWN_WORDS) & (F.col("known") < LEAST_KNOWN))
    language = F.when(rejected, UNDETERMINED).otherwise(F.element_at(names, F.array_position("_score", F.col("_top")).cast("int")))
    return out.withColumn("language", language).select(*rows.columns, "language", F.round("posterior", 6).alias("posterior"), "text_language")


def document_rows(docs: DataFrame, whole: bool = False) -> DataFrame:
    """doc_id, text and the evidence columns of a documents table: declared language, and source as host.

    ``whole``: the row itself as a struct ``row`` instead of doc_id, so that no column name can clash.
    """
    first = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row") if whole else F.col("doc_id")
    none = F.lit(None).cast("string")
    return docs.select(first, "text", F.col("source").alias("host"), none.alias("domain"), none.alias("suffix"), F.lower("lang").alias("declared"))


def declared_language(html: Column) -> Column:
    return F.lower(F.nullif(F.regexp_extract(html, r"(?i)<html\b[^>]*?\blang\s*=\s*[\"']?\s*([A-Za-z]{2,3})", 1), F.lit("")))


def page_texts(pages: DataFrame) -> DataFrame:
    """page_id and evidence columns of raw pages; the text is the page's own main text."""
    from stseq.llm.html import main_blocks
    from stseq.llm.urlrep import registered_domain, suffix, url_host

    host = F.nullif(url_host(F.col("url")), F.lit(""))
    rows = pages.select("page_id", host.alias("host"), registered_domain(host).alias("domain"), suffix(host).alias("suffix"), declared_language(F.col("html")).alias("declared"), "html")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            text = ["\n".join(main_blocks(h or "", frozenset())) for h in b.column(5).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(text, pa.string())], names=[*b.schema.names[:5], "text"])

    kind = pages.schema["page_id"].dataType.simpleString()
    return rows.mapInArrow(run, f"page_id {kind}, host string, domain string, suffix string, declared string, text string")


def keep_identified(docs: DataFrame) -> DataFrame:
    """Rows of a documents table whose language is determined; its columns only."""
    model = fit_text_model(docs)
    return identify(document_rows(docs, whole=True), model).where(F.col("language") != UNDETERMINED).select("row.*")
