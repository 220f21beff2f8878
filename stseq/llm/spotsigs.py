"""Spot signatures with DataFrame functions only: fingerprints of texts and pruned Jaccard near-duplicate search.

A signature is the chain of the next ``CHAIN`` content words after a common word (an anchor); runs of anchors
count as one. A text's fingerprint is its set of signature hashes. A text where no content word follows an anchor
takes a chain from each of its words, one without letters or digits its own hash, the empty text nothing.

The search partitions sets by length: two sets reach a Jaccard similarity of t only if the smaller has at
least t times the size of the larger, and share one of the rarest signatures (a prefix) of each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stseq.llm.common import connected_components, inline_rows, stored

CHAIN = 3
#: Anchors, common words of English, French, German and Spanish.
ANCHORS = (
    "a an and are as at be but by for from had has have he her his if in is it its not of on or she that the their they this to was we were what which who will with you "
    "au aux avec ce ces dans de des du elle en est et il ils je la le les leur lui mais ne nous on ont ou par pas plus pour qu que qui sa se ses son sont sur un une vous "
    "aber als am auch auf aus bei bis das dass dem den der des die ein eine einem einen einer er es für hat ich ihr im ist mit nach nicht noch nur oder sich sie sind so um und von vor war wie wird zu zum zur über "
    "al como con cuando del el ella ellos entre era esta este esto fue ha hay las lo los más me mi muy no o para pero por porque si sin sobre su sus también te todo y ya"
)
#: Ranges of doc_id at most (1.5 GB of a 100 TB table each), and bounds in one step of their search.
_MAX_BUCKETS, _STEP = 1 << 16, 256


def _alternatives(words: list[str]) -> str:
    """One pattern for the words, grouped by first letter so that most words fail at once."""
    groups: dict[str, list[str]] = {}
    for w in words:
        groups.setdefault(w[0], []).append(w[1:])
    return "|".join(f"{c}(?:{'|'.join(sorted(rest, key=lambda r: (-len(r), r)))})" for c, rest in sorted(groups.items()))


def signature_hashes(text: Column, chain: int = CHAIN, anchors: str = ANCHORS) -> Column:
    """Sorted array of the distinct 32-bit signature hashes of a text (not null)."""
    anchor = _alternatives(sorted(set(anchors.split())))
    plain = F.trim(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "))

    def chains(tail: Column) -> Column:
        # parts end in a space each, so joined they are words parted by single spaces
        def one(s: Column, i: Column) -> Column:
            return F.hash(F.trim(F.substring_index(F.concat_ws("", s, *[F.get(tail, i + j) for j in range(1, chain)]), " ", chain)))

        return F.transform(tail, one)

    def of_tail(tail: Column, words: Column) -> Column:
        return F.when(F.size(tail) > 0, chains(tail)).otherwise(_let(F.transform(words, lambda w: F.concat(w, F.lit(" "))), chains))

    def of_plain(p: Column) -> Column:
        # one anchor a match: a repeated group would take the stack of Java's regular expressions for each repetition
        parts = F.split(F.concat(F.lit(" "), p, F.lit(" ")), f"(?<= )(?:{anchor}) ")
        tail = _let(parts, lambda x: F.filter(F.slice(x, F.lit(2), F.greatest(F.size(x) - 1, F.lit(0))), lambda s: s != ""))
        none = F.when(text == "", F.array().cast("array<int>")).otherwise(F.array(F.hash(text)))
        return F.when(p == "", none).otherwise(_let(tail, lambda t: of_tail(t, F.split(p, " "))))

    return F.array_sort(F.array_distinct(_let(plain, of_plain)))


def _let(value: Column, body) -> Column:
    """``body(value)`` with the value taken once, not once for each element of the lambdas inside."""
    return F.transform(F.array(value), body)[0]


def fingerprint_text(hashes: Column) -> Column:
    """The set as a string: its 32-bit hashes in order, base64."""
    return F.base64(F.unhex(F.array_join(F.transform(hashes, lambda h: F.lpad(F.hex(h.cast("long").bitwiseAND(F.lit(0xFFFFFFFF))), 8, "0")), "")))


def likeness(a: Column, b: Column) -> Column:
    """Jaccard similarity of two hash sets; two empty sets are alike."""
    both = F.size(F.array_intersect(a, b))
    total = F.size(a) + F.size(b) - both
    return F.when(total == 0, 1.0).otherwise(both / total).cast("double")


def _listed(values: list, kind: str) -> Column:
    """A long list as one constant of the plan."""
    return F.split(F.lit(",".join(map(str, values))), ",").cast(f"array<{kind}>")


def _id_buckets(docs: DataFrame, rows: int = 128) -> tuple[Column, DataFrame]:
    """Bucket of a doc_id by approximate quantiles, and the ids that begin a bucket with the bucket before it (a row a bucket)."""
    n = docs.count()
    buckets = min(_MAX_BUCKETS, max(1, n // rows))
    points = _listed([i / buckets for i in range(1, buckets)], "double")
    bounds = sorted(set(docs.agg(F.percentile_approx("doc_id", points, max(100_000, 4 * buckets))).first()[0] or [])) if buckets > 1 else []
    doc_id = F.col("doc_id")
    if not bounds:
        bucket = F.lit(0)
    else:  # two levels
        level = F.size(F.filter(_listed(bounds[::_STEP], "bigint"), lambda b: b < doc_id))
        fine = F.slice(_listed(bounds, "bigint"), F.greatest(level - 1, F.lit(0)) * _STEP + 1, _STEP)
        bucket = F.when(doc_id.isNull() | (level == 0), 0).otherwise((level - 1) * _STEP + F.size(F.filter(fine, lambda b: b < doc_id)))
    firsts = docs.select(bucket.alias("b"), "doc_id").groupBy("b").agg(F.min("doc_id").alias("first"), F.count(F.when(doc_id.isNull(), 1)).alias("nulls")).collect()
    firsts = sorted((r["b"], None if r["nulls"] else r["first"]) for r in firsts)
    guests = [(first, firsts[i - 1][0]) for i, (_, first) in enumerate(firsts)]
    spark = docs.sparkSession
    known = inline_rows(spark, [g for g in guests if g[0] is not None], ["_first", "_guest"])
    none = [g[1] for g in guests if g[0] is None]  # rows without an id come first of all
    if none:
        known = known.unionByName(spark.sql(f"SELECT CAST(NULL AS BIGINT) AS _first, {none[0]}L AS _guest"))
    return bucket.cast("long"), known


def fingerprint_documents(docs: DataFrame, chain: int = CHAIN) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next for every row.

    The edited text ends in the beginning of the next document's text, by doc_id (then text), in place of its own last
    quarter; the first document follows the last. Rows are dealt once, by ranges of doc_id; the first document of
    a range is also sent to the range before it. A null text counts as empty; rows of equal id are each other's
    neighbours; a table of one row follows itself; an empty table gives an empty result.
    """
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    bucket, guests = _id_buckets(texts)
    dealt = (
        texts.withColumn("marks", signature_hashes(F.col("text"), chain))
        .withColumn("home", bucket)
        .join(F.broadcast(guests), F.col("doc_id").eqNullSafe(F.col("_first")), "left")
        .withColumn("at", F.explode(F.filter(F.array(
            F.struct(F.col("home").alias("bucket"), F.lit(0).alias("guest")), F.struct(F.col("_guest").alias("bucket"), F.lit(1).alias("guest"))
        ), lambda x: x["bucket"].isNotNull())))
        .select("doc_id", "text", "marks", "at.bucket", "at.guest")
    )
    order = Window.partitionBy("bucket").orderBy("guest", F.col("doc_id").asc_nulls_first(), "text")
    placed = dealt.select(
        "doc_id", "text", "marks", "guest", F.lead("text").over(order).alias("next_text"), F.lead("marks").over(order).alias("next_marks")
    ).where("guest = 0")
    n = F.char_length("text")
    cut = F.expr("char_length(text) div 4").cast("int")
    edited = F.concat(F.substring("text", F.lit(1), n - cut), F.substring("next_text", F.lit(1), cut))
    made = placed.select("doc_id", n.cast("long").alias("n_chars"), "marks", "next_marks", edited.alias("edited"))
    made = made.withColumn("edited_marks", signature_hashes(F.col("edited"), chain))
    return made.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), fingerprint_text(F.col("marks")).alias("fingerprint"),
        fingerprint_text(F.col("edited_marks")).alias("edited_fingerprint"), likeness(F.col("marks"), F.col("edited_marks")).alias("near_edited"),
        likeness(F.col("marks"), F.col("next_marks")).alias("near_next"),
    )


def near_classes(docs: DataFrame, threshold: float = 0.8, chain: int = CHAIN) -> tuple[DataFrame, DataFrame]:
    """(membership: doc_id, class_id; pairs: a, b, similarity) of fingerprints alike by ``threshold`` or more.

    Rows of equal fingerprint form one class (smallest doc_id); pairs are between classes. Each set joins on its
    rarest signatures only (|s| - ceil(t*|s|) + 1 of them), within the length partitions that can reach the
    threshold; the exact similarity is taken last. Sets without signatures pair with nothing.
    """
    marked = stored(docs.select("doc_id", signature_hashes(F.coalesce(F.col("text"), F.lit("")), chain).alias("marks")), "marks")
    classes = stored(marked.groupBy("marks").agg(F.min("doc_id").alias("class_id")).withColumn("n", F.size("marks")), "classes")
    spread = classes.select("class_id", "n", F.explode("marks").alias("mark"))
    counts = spread.groupBy("mark").agg(F.count("*").alias("df"))
    width = F.expr(f"n - cast(ceil({threshold}D * n - 1e-9) as int) + 1")
    prefix = (
        spread.join(counts, "mark").groupBy("class_id", "n").agg(F.array_sort(F.collect_list(F.struct("df", "mark"))).alias("rare"))
        .select("class_id", "n", F.explode(F.slice("rare", F.lit(1), width)).alias("r"))
        .select("class_id", "n", F.col("r.mark").alias("mark"), F.col("r.df").alias("df")).where("df > 1")
    )
    # length partitions: geometric steps of 1/t, so partners lie in the same or the next one
    import math

    step = math.log(1 / threshold)
    part = F.floor(F.log(F.col("n").cast("double")) / step).cast("int")
    left = prefix.select(F.col("class_id").alias("a"), F.col("n").alias("an"), "mark", part.alias("part"))
    right = prefix.select(F.col("class_id").alias("b"), F.col("n").alias("bn"), "mark", F.explode(F.array(part, part - 1, part + 1)).alias("part"))
    close = (F.col("an") >= threshold * F.col("bn")) & (F.col("bn") >= threshold * F.col("an"))
    found = left.join(right, ["mark", "part"]).where((F.col("a") < F.col("b")) & close).select("a", "b").distinct()
    one = classes.select(F.col("class_id").alias("a"), F.col("marks").alias("am"))
    two = classes.select(F.col("class_id").alias("b"), F.col("marks").alias("bm"))
    pairs = found.join(one, "a").join(two, "b").select("a", "b", likeness(F.col("am"), F.col("bm")).alias("similarity")).where(F.col("similarity") >= threshold)
    members = marked.join(classes.select("marks", "class_id"), "marks").select("doc_id", "class_id")
    return members, pairs


def near_components(docs: DataFrame, threshold: float = 0.8) -> DataFrame:
    """doc_id, component_id: classes joined over pairs."""
    members, pairs = near_classes(docs, threshold)
    parts = connected_components(pairs.select(F.col("a").alias("src"), F.col("b").alias("dst")))
    return members.join(parts, F.col("class_id") == F.col("node"), "left").select("doc_id", F.coalesce("component", "class_id").alias("component_id"))
