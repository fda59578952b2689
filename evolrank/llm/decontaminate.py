"""Benchmark decontamination by spaced seeds, in built-in functions only.

A seed mask looks at some of the words in a short span and ignores the others,
so substituted words at ignored places do not hide a match.  Training and
benchmark words are hashed under the same fixed masks and joined on the hash.
Around each hit the two texts are laid side by side (same diagonal) and the
words of an aligned window are compared; enough equal words make it a leak, in
the whole window or in any LEAST_WINDOW neighbouring words of it.  An item with
fewer words than that must lie side by side with the document as a whole.
OP3_SQL states the rule of the whole window only: it lacks the pairs that a
stretch or a short item alone shows.

The document side is one streamed pass: positions are exploded beside the word
array, hashed, and probed; only hits go on.  The benchmark side is broadcast
when its counted seeds are few, and joined by a shuffle otherwise.

Words are runs of letters and digits, lower-cased.  Defined results: null and
empty texts hold nothing; benchmark items with fewer words than a mask's span
cannot seed and never match; repeated rows and ties give one row per (document
id, item id), repeated document rows add to its windows, repeated item rows do
not, and each different text of an item id is compared; rows with a null id take no part in the answer; other columns
are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, text_of

# The masks (1: the word counts, 0: it is ignored).
MASKS = ("1101011", "11100100111")
WINDOW = 24  # aligned words compared around a hit
LEAST_WINDOW = 12
LEAST_SHARE = 0.75
BROADCAST_SEEDS = 1_000_000


def word_array(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def seeds(texts: DataFrame, words: str, keep: list[str]) -> DataFrame:
    """(keep..., words, pos, seed): one row for each mask and position.

    The array stays beside its exploded positions within one code-generated
    stage, so it is neither copied nor shuffled.
    """
    spread = texts.where(F.size(words) >= min(map(len, MASKS))).select(*keep, words, F.size(words).alias("n"), F.explode(F.sequence(F.lit(0), F.size(words) - min(map(len, MASKS)))).alias("pos"))
    made = []
    for k, mask in enumerate(MASKS):
        used = [i for i, c in enumerate(mask) if c == "1"]
        seed = F.xxhash64(F.lit(k), *[F.get(F.col(words), F.col("pos") + i) for i in used])
        made.append(F.when(F.col("pos") + len(mask) <= F.col("n"), seed))
    return spread.select(*keep, words, "n", "pos", F.explode(F.array(*made)).alias("seed")).where(F.col("seed").isNotNull())


def _verified(hits: DataFrame) -> DataFrame:
    """(d, b, times, n_equal, n_aligned, x, y) from hits (d, dw, n, pos, b, bw, m, bat, hits).

    The window on the item is centred on the hit and clipped to what both texts
    have on this diagonal.  Only the two short windows leave the probing stage;
    equal pairs of windows are counted before the shuffle and compared after it.
    """
    shift = F.col("pos") - F.col("bat")
    lo = F.greatest(F.lit(0), -shift, F.col("bat") - (WINDOW - len(MASKS[0])) // 2)
    size = F.least(F.col("m"), F.col("n") - shift, lo + WINDOW) - lo
    windows = hits.where(size >= F.least(F.lit(LEAST_WINDOW), F.col("m"))).select("d", "b", F.slice("dw", lo + shift + 1, size).alias("x"), F.slice("bw", lo + 1, size).alias("y"), "hits")
    counted = windows.groupBy("d", "b", "x", "y").agg(F.sum("hits").alias("times"))
    same = F.aggregate(F.zip_with("x", "y", lambda p, q: (p == q).cast("int")), F.lit(0), lambda t, e: t + e)
    return counted.select("d", "b", "times", same.alias("n_equal"), F.size("x").alias("n_aligned"), "x", "y")


def _best_stretch(x: str, y: str) -> Column:
    """Most equal words in any LEAST_WINDOW neighbouring places of two aligned windows (in all, if they are shorter)."""
    equal = F.zip_with(x, y, lambda p, q: (p == q).cast("int"))
    starts = F.sequence(F.lit(1), F.greatest(F.lit(1), F.size(x) - LEAST_WINDOW + 1))
    return F.array_max(F.transform(starts, lambda at: F.aggregate(F.slice(equal, at, LEAST_WINDOW), F.lit(0), lambda t, e: t + e)))


def leak_hits(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """(d, b, times, n_equal, n_aligned, x, y) of every window around a hit.

    Both paths count one hit for each (document row, position, mask, item id,
    different words of the item, place in them).
    """
    text = text_of(docs, text_col)
    d = docs.where(docs[id_col].isNotNull()).select(docs[id_col].alias("d"), F.xxhash64(text).alias("tk"), word_array(text).alias("dw"))
    b = benchmark.where(benchmark[item_col].isNotNull()).select(benchmark[item_col].alias("b"), word_array(text_of(benchmark, item_text)).alias("bw")).distinct()
    right = seeds(b, "bw", ["b"]).select("b", "bw", F.col("n").alias("m"), F.col("pos").alias("bat"), "seed")
    if right.limit(BROADCAST_SEEDS + 1).count() <= BROADCAST_SEEDS:
        return _verified(seeds(d, "dw", ["d"]).join(F.broadcast(right), "seed").withColumn("hits", F.lit(1)))
    # Many benchmark seeds: places only are shuffled, words are fetched for the hits.
    b = b.withColumn("bk", F.xxhash64("bw"))
    right = seeds(b, "bw", ["b", "bk"]).select("b", "bk", F.col("pos").alias("bat"), "seed")
    places = seeds(d, "dw", ["d", "tk"]).select("d", "tk", "pos", "seed")
    hits = places.join(right, "seed").groupBy("d", "tk", "pos", "b", "bk", "bat").agg(F.count(F.lit(1)).alias("hits"))
    words = d.dropDuplicates(["d", "tk"]).withColumn("n", F.size("dw"))
    return _verified(hits.join(words, ["d", "tk"]).join(b.withColumn("m", F.size("bw")), ["b", "bk"]))


def leaks(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """(doc_id, item_id, n_windows, best_equal): contaminated documents and what they hold.

    Both figures are those of the agreeing windows; a pair without any has those
    of the agreeing stretches instead.
    """
    # Judged inside the aggregate: a filter here would be pushed into the probe and break its generated code.
    whole = (F.col("n_aligned") >= LEAST_WINDOW) & (F.col("n_equal") >= LEAST_SHARE * F.col("n_aligned"))
    stretch = F.when(~whole, _best_stretch("x", "y"))
    part = stretch >= LEAST_SHARE * F.least(F.lit(LEAST_WINDOW), F.col("n_aligned"))
    return (
        leak_hits(docs, benchmark, id_col, text_col, item_col, item_text)
        .groupBy("d", "b")
        .agg(
            F.sum(F.when(whole, F.col("times"))).alias("windows"), F.max(F.when(whole, F.col("n_equal"))).alias("window_equal"),
            F.sum(F.when(part, F.col("times"))).alias("stretches"), F.max(F.when(part, stretch)).alias("stretch_equal"),
        )
        .select(F.col("d").alias("doc_id"), F.col("b").alias("item_id"), F.coalesce("windows", "stretches").alias("n_windows"), F.coalesce("window_equal", "stretch_equal").cast("int").alias("best_equal"))
        .where("n_windows > 0")
    )


def decontaminate(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` whose document holds no benchmark passage; rows with a null id stay."""
    bad = leaks(docs, benchmark, id_col, text_col).select(F.col("doc_id").alias("bad_id")).distinct()
    return docs.join(bad, docs[id_col] == bad["bad_id"], "left_anti")


def op3_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))


def _sql() -> str:
    parts = []
    for k, mask in enumerate(MASKS):
        used = [i for i, c in enumerate(mask) if c == "1"]
        seed = " || ' ' || ".join(f"w[pos + {i + 1}]" for i in used)
        parts.append(f"SELECT id, w, n, pos, '{k} ' || {seed} AS seed FROM {{0}}_at WHERE pos + {len(mask)} <= n")
    def side(name: str, source: str, key: str) -> str:
        body = " UNION ALL ".join(parts).replace("{0}", name)
        return f"""{name}_w AS (SELECT {key} AS id, list_filter(string_split_regex(lower(coalesce(text, '')), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '') AS w FROM {source} WHERE {key} IS NOT NULL),
{name}_at AS (SELECT id, w, len(w) AS n, unnest(range(0, len(w))) AS pos FROM {name}_w),
{name}_s AS ({body})"""
    return f"""WITH {side('d', 'documents', 'doc_id')},
{side('b', 'benchmark', 'item_id')},
bs AS (SELECT DISTINCT id, w, n, pos, seed FROM b_s),
hits AS (
  SELECT d.id AS doc_id, bs.id AS item_id, d.w AS dw, bs.w AS bw, d.pos - bs.pos AS shift,
         greatest(0, bs.pos - d.pos, bs.pos - {(WINDOW - len(MASKS[0])) // 2}) AS lo, bs.n AS m, d.n AS n
  FROM d_s d JOIN bs ON d.seed = bs.seed),
spans AS (SELECT *, least(m, n - shift, lo + {WINDOW}) - lo AS size FROM hits),
judged AS (
  SELECT doc_id, item_id, size,
         len(list_filter(range(0, size), lambda i: dw[lo + shift + i + 1] = bw[lo + i + 1])) AS same
  FROM spans WHERE size >= {LEAST_WINDOW})
SELECT doc_id, item_id, count(*) AS n_windows, CAST(max(same) AS INTEGER) AS best_equal
FROM judged WHERE same >= {LEAST_SHARE} * size GROUP BY doc_id, item_id"""


OP3_SQL = _sql()
