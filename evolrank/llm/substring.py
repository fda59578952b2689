"""Substring deduplication with compressed FM-indexes over anchored regions.

A window is a run of WINDOW consecutive words; a word goes if a window that
covers it also starts earlier in the corpus.  Two equal windows have the same
anchor: the k-word run with the smallest hash among all runs inside the window.
So only anchors that occur twice (exactly counted over the corpus) matter, and
only the few words around them can take part in a repeated window.

1. Anchors of every text are found (numpy sliding minimum) and counted; exact
   copies of whole texts are settled by their digest beforehand.
2. Equal regions around a repeated anchor are found by digest and collapse to
   their first occurrence; every later occurrence goes as a whole.
3. Words are cut out for anchors whose regions differ, and only for these.  The
   different regions of an anchor are indexed per shard: a Burrows-Wheeler
   transform in a wavelet matrix of packed bit vectors.  All windows of all
   regions are streamed through backward search at once; a window whose suffix
   range holds an earlier start is reported.  Shards are bounded; an anchor
   with more different regions than a shard may hold is settled by exact
   window digests and a grouped minimum instead.

Order of starts is (doc_id, position).  Defined results: null text has no words;
texts shorter than a window lose nothing; rows with a null doc_id neither lose
words nor take them from others; rows that repeat a doc_id count as one document
whose positions are compared as numbers.  Further columns are ignored.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bitfilter import bit_filter
from .common import WORD_PATTERN, map_texts, materialise, release, table
from .shingles import encode, mix, powers, run_hashes, word_hashes, word_spans

WINDOW = 20
ANCHOR = 10
SHARD_REGIONS = 6_000  # regions that a shard holds on average
HOT_REGIONS = 20_000  # different regions of one anchor beyond which digests take over
_WORDS = re.compile(WORD_PATTERN)


def _sliding(x: np.ndarray, span: int, best) -> np.ndarray:
    """``best`` (np.minimum or np.maximum) over every run of ``span`` values, by doubling."""
    n, out, width = len(x) - span + 1, x, 1
    while 2 * width <= span:
        out = best(out[:-width], out[width:])
        width *= 2
    return best(out[:n], out[span - width : span - width + n])


def anchor_positions(words: np.ndarray, window: int = WINDOW, k: int = ANCHOR) -> tuple[np.ndarray, np.ndarray]:
    """Places and hashes of the runs that are smallest in some window (all of them on ties)."""
    if len(words) < window:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    h = run_hashes(words, k)
    span = window - k + 1
    least = _sliding(h, span, np.minimum)
    pad = np.zeros(span - 1, np.uint64)
    reach = _sliding(np.concatenate([pad, least, pad]), span, np.maximum)
    at = np.flatnonzero(reach == h)
    return at, h[at]


class WaveletMatrix:
    """Rank queries over a sequence of small integers, one packed bit vector a level."""

    def __init__(self, values: np.ndarray, symbols: int):
        self.levels = max(1, int(symbols - 1).bit_length())
        self.words, self.counts, self.zeros = [], [], []
        v = values
        for level in reversed(range(self.levels)):
            bit = (v >> level) & 1
            packed = np.packbits(bit.astype(np.uint8), bitorder="little")
            packed = np.concatenate([packed, np.zeros(16 - len(packed) % 8, np.uint8)]).view(np.uint64)
            self.words.append(packed)
            self.counts.append(np.concatenate([[0], np.cumsum(np.bitwise_count(packed))]).astype(np.int64))
            self.zeros.append(len(v) - int(bit.sum()))
            v = np.concatenate([v[bit == 0], v[bit == 1]])
        self.base = self._walk(np.arange(symbols), np.zeros(symbols, np.int64))

    def _walk(self, c: np.ndarray, i: np.ndarray) -> np.ndarray:
        for depth, level in enumerate(reversed(range(self.levels))):
            block = i >> 6
            below = self.words[depth][block] & ((np.uint64(1) << (i & 63).astype(np.uint64)) - np.uint64(1))
            ones = self.counts[depth][block] + np.bitwise_count(below)
            i = np.where((c >> level) & 1 == 1, self.zeros[depth] + ones, i - ones)
        return i

    def rank(self, c: np.ndarray, i: np.ndarray) -> np.ndarray:
        """How often symbol c[j] occurs before place i[j]."""
        return self._walk(c, i) - self.base[c]


def suffix_order(text: np.ndarray, depth: int) -> np.ndarray:
    """Suffixes sorted by at least their first ``depth`` symbols (prefix doubling)."""
    rank, size = text.astype(np.int64), 1
    order = np.argsort(rank, kind="stable")
    while size < depth:
        nxt = np.full(len(rank), -1, np.int64)
        nxt[: len(rank) - size] = rank[size:]
        key = rank * (int(rank.max()) + 2) + nxt + 1
        order = np.argsort(key, kind="stable")
        step = np.diff(key[order], prepend=key[order[:1]]) != 0
        rank = np.empty_like(rank)
        rank[order] = np.cumsum(step)
        size *= 2
    return order


class FmIndex:
    """Backward search over the regions of one shard, with the earliest start of each suffix range."""

    def __init__(self, text: np.ndarray, starts: np.ndarray, window: int):
        symbols = int(text.max()) + 1
        order = suffix_order(text, window + 1)
        self.bwt = WaveletMatrix(text[order - 1], symbols)
        self.first = np.concatenate([[0], np.cumsum(np.bincount(text, minlength=symbols))])
        self.low = [starts[order]]
        while 2 ** len(self.low) <= len(text):
            half, last = 2 ** (len(self.low) - 1), self.low[-1]
            self.low.append(np.minimum(last[:-half], last[half:]))

    def earliest(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        level = np.frexp((hi - lo).astype(float))[1] - 1
        out = np.empty(len(lo), np.int64)
        for k in np.unique(level):
            pick = level == k
            out[pick] = np.minimum(self.low[k][lo[pick]], self.low[k][hi[pick] - 2**k])
        return out

    def stream(self, text: np.ndarray, begins: np.ndarray, ends: np.ndarray, starts: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(region, from, to) text intervals of matches of at least ``window`` symbols with an earlier start.

        All regions are read backwards at once, one symbol a round.  A lane
        extends its match while the suffix range still holds another occurrence,
        and from ``window`` symbols on an earlier one.  A long match is reported
        whole; the next match of that region must then reach further left, so
        its end moves to where only windows not yet covered are left.
        """
        lane = np.flatnonzero(ends - begins >= window)
        end, size = ends[lane].copy(), np.zeros(len(lane), np.int64)
        lo, hi = np.zeros(len(lane), np.int64), np.full(len(lane), len(text), np.int64)
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        while len(lane):
            at = end - size - 1
            more = at >= begins[lane]
            c = text[np.maximum(at, 0)]
            new_lo, new_hi = self.first[c] + self.bwt.rank(c, lo), self.first[c] + self.bwt.rank(c, hi)
            good = more & (new_hi - new_lo > 1)
            long_ = np.flatnonzero(good & (size + 1 >= window))
            if len(long_):
                good[long_] = self.earliest(new_lo[long_], new_hi[long_]) < starts[at[long_]]
            stuck = ~good
            hit = stuck & (size >= window)
            if hit.any():
                found.append((lane[hit], end[hit] - size[hit], end[hit]))
            # After a report every window up to the match's left edge is covered: go on one symbol beyond it.
            end = np.where(hit, end - size + window - 1, np.where(stuck, end - 1, end))
            size = np.where(stuck, 0, size + 1)
            lo, hi = np.where(stuck, 0, new_lo), np.where(stuck, len(text), new_hi)
            keep = (end - begins[lane] >= window) & (more | ~hit)
            if not keep.all():
                lane, end, size, lo, hi = lane[keep], end[keep], size[keep], lo[keep], hi[keep]
        if not found:
            none = np.zeros(0, np.int64)
            return none, none, none
        return tuple(np.concatenate([f[i] for f in found]) for i in range(3))


def repeated_in_shard(docs: np.ndarray, starts: np.ndarray, regions: list[str], window: int = WINDOW) -> list[tuple[int, int, int]]:
    """(region, from, to) word intervals, within regions, that are covered by windows with an earlier start."""
    number: dict[str, int] = {}
    coded = [[number.setdefault(w, len(number) + 1) for w in r.split(" ")] for r in regions]
    sizes = np.array([len(c) for c in coded], dtype=np.int64)
    offsets = np.concatenate([[0], np.cumsum(sizes + 1)])[:-1]
    text = np.zeros(int((sizes + 1).sum()), dtype=np.int64)  # 0 stands between regions
    owner = np.repeat(np.arange(len(coded)), sizes + 1)
    inner = np.arange(len(text)) - offsets[owner]
    text[inner < sizes[owner]] = np.concatenate([np.asarray(c, dtype=np.int64) for c in coded])
    # Starts as ranks of (document, position): equal starts get equal ranks.
    d, p = docs[owner], starts[owner] + inner
    order = np.lexsort((p, d))
    fresh = (np.diff(d[order], prepend=-1) != 0) | (np.diff(p[order], prepend=-1) != 0)
    when = np.empty(len(text), np.int64)
    when[order] = np.cumsum(fresh)
    region, f, t = FmIndex(text, when, window).stream(text, offsets, offsets + sizes, when, window)
    return list(zip(region.tolist(), (f - offsets[region]).tolist(), (t - offsets[region]).tolist(), strict=True))


def region_prints(words: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each run words[start:end], from sums of all words before a place."""
    up, down = powers(len(words) + 1), powers(len(words) + 1, inverse=True)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(words * up[: len(words)])])
    return mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def anchors(docs: DataFrame, window: int = WINDOW, k: int = ANCHOR) -> DataFrame:
    """(d, tag, found array<struct<ah,rh,start,n>>): anchors of every text long enough, each with the region around it.

    A region holds all windows of an anchor: n words from ``start``, with the digest rh.  docs: (d, tag, text).
    """
    def start():
        def work(texts):
            parts: list[list[np.ndarray]] = [[], [], [], []]
            for t in texts:
                raw = encode(t)
                words = word_hashes(raw, *word_spans(raw), fold=False)
                at, h = anchor_positions(words, window, k)
                begins, ends = np.maximum(at - (window - k), 0), np.minimum(at + window, len(words))
                for held, x in zip(parts, (h.view(np.int64), region_prints(words, begins, ends).view(np.int64), begins.astype(np.int32), (ends - begins).astype(np.int32)), strict=True):
                    held.append(x)
            ends = np.concatenate([[0], np.cumsum([len(x) for x in parts[0]])]).astype(np.int32)
            kinds = (np.int64, np.int64, np.int32, np.int32)
            fields = pa.StructArray.from_arrays([np.concatenate([np.zeros(0, t), *x]) for t, x in zip(kinds, parts, strict=True)], ["ah", "rh", "start", "n"])
            return {"found": pa.ListArray.from_arrays(ends, fields)}

        return work

    keyed = docs.select(F.struct("d", "tag").alias("k"), "text")
    found = map_texts(keyed, start, "found array<struct<ah:long,rh:long,start:int,n:int>>", "k")
    return found.where(F.size("found") > 0).select("k.d", "k.tag", "found")


def region_rows(docs: DataFrame, places: DataFrame) -> DataFrame:
    """(d, tag, ah, kinds, start, region): the words of each region; places: (d, tag, found array<struct<ah,kinds,start,n>>)."""
    joined = docs.join(places, ["d", "tag"]).select("d", "tag", "text", "found")
    names = ("d", "tag", "ah", "kinds", "start", "region")

    def run(batches):
        for batch in batches:
            ds, tags, texts, founds = (batch.column(i) for i in range(4))
            schema = pa.schema([("d", ds.type), ("tag", pa.int64()), ("ah", pa.int64()), ("kinds", pa.int64()), ("start", pa.int64()), ("region", pa.string())])
            out: dict = {c: [] for c in names}
            for i in range(len(batch)):
                words, values = _WORDS.findall(texts[i].as_py()), founds[i].values
                starts, sizes = values.field("start").to_pylist(), values.field("n").to_pylist()
                out["d"] += [ds[i].as_py()] * len(starts)
                out["tag"] += [tags[i].as_py()] * len(starts)
                out["ah"] += values.field("ah").to_pylist()
                out["kinds"] += values.field("kinds").to_pylist()
                out["start"] += starts
                out["region"] += [" ".join(words[a : a + n]) for a, n in zip(starts, sizes, strict=True)]
                if len(out["ah"]) > 20_000:  # one text's regions at most beyond this
                    yield pa.RecordBatch.from_pydict(out, schema=schema)
                    out = {c: [] for c in names}
            yield pa.RecordBatch.from_pydict(out, schema=schema)

    kind = docs.schema["d"].dataType.simpleString()
    return joined.mapInArrow(run, f"d {kind}, tag long, ah long, kinds long, start long, region string")


def _hot_windows(regions: DataFrame, window: int) -> DataFrame:
    """Intervals for anchors with very many different regions: digests of windows, smallest start per digest."""
    words = F.split("region", " ")
    spread = regions.select("d", "tag", "start", words.alias("w"), F.explode(F.sequence(F.lit(0), F.size(words) - window)).alias("o")).select(
        "d", "tag", (F.col("start") + F.col("o")).alias("at"), F.concat_ws(" ", F.slice("w", F.col("o").cast("int") + 1, window)).alias("s")
    )
    spread = spread.select("d", "tag", "at", F.xxhash64("s").alias("w1"), F.xxhash64(F.lit(5), "s").alias("w2")).distinct()
    first = spread.groupBy("w1", "w2").agg(F.min(F.struct("d", "at")).alias("m"), F.count(F.lit(1)).alias("c")).where("c > 1")
    return spread.join(first, ["w1", "w2"]).where(F.struct("d", "at") > F.col("m")).select("d", "tag", F.col("at").alias("f"), (F.col("at") + window).alias("t"))


def repeated_intervals(docs: DataFrame, window: int = WINDOW, k: int = ANCHOR, hot: int = HOT_REGIONS) -> DataFrame:
    """(d, tag, f, t): word intervals [f, t) covered by windows that start earlier; docs: (d, tag, text), no exact copies."""
    found = materialise(anchors(docs, window, k))
    spread = found.select("d", "tag", F.explode("found").alias("a")).select("d", "tag", "a.ah", "a.rh", "a.start", "a.n")
    # Counts are written before they are joined: an anchor that fills a third of a table is then split by the planner.
    shared = materialise(spread.groupBy("ah").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("ah"))
    places = materialise(spread.join(shared, "ah", "left_semi"))
    release(found, shared)
    firsts = materialise(places.groupBy("ah", "rh").agg(F.min(F.struct("d", "start", "tag", "n")).alias("m")))
    kept = F.struct(F.col("m.d"), F.col("m.start"), F.col("m.tag"))
    judged = places.join(firsts, ["ah", "rh"]).where(F.struct("d", "start", "tag") > kept)
    later = materialise(judged.select("d", "tag", F.col("start").cast("long").alias("f"), (F.col("start") + F.col("n")).cast("long").alias("t")))
    release(places)
    many = materialise(firsts.groupBy("ah").agg(F.count(F.lit(1)).alias("kinds")).where("kinds > 1"))
    open_ = firsts.join(many, "ah").select("m.d", "m.tag", F.struct("ah", "kinds", "m.start", "m.n").alias("a"))
    wanted = materialise(open_.groupBy("d", "tag").agg(F.collect_list("a").alias("found")))  # of one text
    release(firsts, many)
    keep = bit_filter(wanted.select("d"))
    single = materialise(region_rows(docs.where(keep(F.col("d"))), wanted))
    release(wanted)
    shards = max(1, single.count() // SHARD_REGIONS)

    def search(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values(["d", "start", "tag"], kind="stable")
        d, tag, start = (g[c].to_numpy() for c in ("d", "tag", "start"))
        hits = repeated_in_shard(d, start, g["region"].tolist(), window)
        r = np.array([h[0] for h in hits], dtype=np.int64)
        f, t = (np.array([h[i] for h in hits], dtype=np.int64) for i in (1, 2))
        return pd.DataFrame({"d": d[r], "tag": tag[r], "f": start[r] + f, "t": start[r] + t})

    kind = docs.schema["d"].dataType.simpleString()
    searched = (
        single.where(F.col("kinds") <= hot).withColumn("shard", F.pmod(F.xxhash64("ah"), F.lit(shards)))
        .groupBy("shard").applyInPandas(search, f"d {kind}, tag long, f long, t long")
    )
    return later.unionByName(searched).unionByName(_hot_windows(single.where(F.col("kinds") > hot), window))


def dedup_substrings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, k: int = ANCHOR, hot: int = HOT_REGIONS) -> DataFrame:
    """(id, intervals array<struct<f,t>>, text, is_copy) for every row; intervals are the words to drop."""
    text = F.coalesce(docs[text_col].cast("string"), F.lit(""))
    base = docs.select(docs[id_col].alias("d"), text.alias("text"))
    repeats = not base.where(F.col("d").isNotNull()).groupBy("d").count().where("count > 1").isEmpty()
    base = base.withColumn("tag", F.xxhash64("text") if repeats else F.lit(0).cast("long"))
    digests = base.where(F.col("d").isNotNull()).select("d", "tag", F.xxhash64("text").alias("x1"), F.xxhash64(F.lit(9), "text").alias("x2"))
    first = digests.groupBy("x1", "x2").agg(F.min("d").alias("first_d"), F.count(F.lit(1)).alias("c")).where("c > 1")
    copies = materialise(digests.join(first, ["x1", "x2"]).where(F.col("d") > F.col("first_d")).select("d", "tag").distinct())
    maybe_copy = bit_filter(copies.select("d"))
    usable = base.where(F.col("d").isNotNull())
    plain = usable.where(~maybe_copy(F.col("d")))
    odd = usable.where(maybe_copy(F.col("d"))).join(copies, ["d", "tag"], "left_anti").select("d", "text", "tag")
    unique = plain.unionByName(odd)
    if repeats:
        unique = unique.dropDuplicates(["d", "tag"])
    found = repeated_intervals(unique, window, k, hot)
    merged = materialise(
        found.groupBy("d", "tag").agg(F.sort_array(F.collect_set(F.struct("f", "t"))).alias("intervals"))
        .unionByName(copies.withColumn("intervals", F.array(F.struct(F.lit(0).cast("long").alias("f"), F.lit((1 << 62)).cast("long").alias("t")))))
    )
    touched = bit_filter(merged.select("d"))
    clean = base.where(F.col("d").isNull() | ~touched(F.coalesce("d", F.lit(0)))).withColumn("intervals", F.lit(None).cast("array<struct<f:long,t:long>>"))
    changed = base.where(F.col("d").isNotNull() & touched(F.coalesce("d", F.lit(0)))).join(merged, ["d", "tag"], "left")
    out = clean.select("d", "text", "intervals").unionByName(changed.select("d", "text", "intervals"))
    return out.withColumnRenamed("d", id_col)


def kept_words(text: str, intervals: list[tuple[int, int]] | None, window: int = WINDOW) -> tuple[int, list[str]]:
    """Number of words, and the words outside the intervals (a copy's interval covers all of a long enough text)."""
    words = _WORDS.findall(text)
    if not intervals or len(words) < window:
        return len(words), words
    kept, at = [], 0
    for f, t in intervals:
        if f > at:
            kept += words[at:f]
        at = max(at, t)
    return len(words), kept + words[at:]


def digest_rows(deduped: DataFrame, id_col: str = "doc_id", window: int = WINDOW) -> DataFrame:
    def run(batches):
        for b in batches:
            n_words, n_removed, sha = [], [], []
            for text, spans in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                n, kept = kept_words(text, [(s["f"], s["t"]) for s in spans] if spans else None, window)
                n_words.append(n)
                n_removed.append(n - len(kept))
                sha.append(hashlib.sha256(" ".join(kept).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(sha, pa.string())], names=[id_col, "n_words", "n_removed", "kept_sha256"])

    kind = deduped.schema[id_col].dataType.simpleString()
    return deduped.select(id_col, "text", "intervals").mapInArrow(run, f"`{id_col}` {kind}, n_words long, n_removed long, kept_sha256 string")


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest_rows(dedup_substrings(table(spark, sf_dir, "documents").select("doc_id", "text")))
