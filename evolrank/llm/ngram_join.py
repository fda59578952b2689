"""Set-similarity self-join on word shingles with adaptive multi-match prefixes.

A pair with similarity t shares at least t times the larger set.  If both sets
are in one global order, the first L shared tokens lie in both L-prefixes
(n - ceil(t n) + L tokens), so a pair that shares fewer than L tokens there can
be skipped.  Every document picks its own L from the document frequencies of its
tokens: a longer prefix costs more postings but lets fewer pairs through to
verification.  A pair is judged by the smaller of its two L.  Across components
the partner's size class is known, which allows shorter prefixes, and documents
with too few open tokens for any partner of a class are left out before the join.

Order of tokens: by hash, but a bounded list of the most frequent tokens comes
last.  The list only steers the order, so it may be approximate without any
effect on the result.  Only prefix tokens are shuffled, and those that a single
document holds are dropped after an exact count over all documents.

Documents with equal sets are one class.  Links inside large groups are first
sought to one leader per posting list, in turns; lists whose members are by then in one
component yield no further pairs, so a group of n near copies does not make n^2
pairs.  All pairs across components are then generated and verified exactly on
the full sets.

Defined results: texts without words have size 0 and are their own component;
null text is empty text; rows that repeat a doc_id are returned each, with the
size of their own set, and share one component (an id is one vertex); rows with
a null doc_id are returned with a null component.  Fingerprints have 64 bits per
shingle and 128 per set.
"""

from __future__ import annotations

import hashlib
import math
from functools import reduce
from operator import and_

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .bitfilter import bit_filter
from .common import map_texts, materialise, release, slices, table
from .components import connected_components
from .shingles import shingle_set

SHINGLE_WORDS = 5
PERCENT = 80
MOST_MATCHES = 6  # largest L that a document may pick
SPARE = 4  # tokens stored beyond the longest prefix, and an eighth of it; a document with more frequent ones is read twice
FREQUENT, MOST_FREQUENT = 32, 200_000  # tokens put last: at least so frequent, at most so many
BATCH_REPEATS = 3  # times a slice of texts must hold a token for it to be counted as possibly frequent
VERIFY_COST = 40.0  # of one verified pair, in postings read
CLASS_RATIO = 1.02  # between neighbouring size classes of a posting list
MOST_CROSS = 4  # largest L across components, where shorter prefixes meet in fewer lists
CLASS_BITS = 63  # of a list's mask of the size classes that its members are in
CROWDED = 0.5  # members met in all lists, for each token of a set, from which the set is compared whole
MOST_TURNS, PAIRS_PER_POSTING = 8, 8  # turns of comparing with leaders, and the pairs a posting that end them


def _print_of(s: np.ndarray) -> np.ndarray:
    """The two halves of a set's 128-bit fingerprint."""
    return np.frombuffer(hashlib.blake2b(s.tobytes(), digest_size=16).digest(), dtype=np.int64)


def _first_print(k: int):
    @F.pandas_udf("long")
    def first(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: int(_print_of(shingle_set(t, k))[0]))

    return first


def owed(n: Column, percent: int) -> Column:
    """Fewest tokens that a set of n tokens shares with a similar one."""
    return F.floor((n * percent + 99) / 100).cast("long")


def _prefix_length(n: int, percent: int) -> int:
    """Tokens of a set of n in the longest prefix that its document may pick."""
    return n + (-percent * n // 100) + MOST_MATCHES


def _list_array(lists: list[np.ndarray]) -> pa.ListArray:
    ends = np.concatenate([[0], np.cumsum([len(x) for x in lists])]).astype(np.int32)
    return pa.ListArray.from_arrays(ends, np.concatenate([np.zeros(0, np.int64), *(x.view(np.int64) for x in lists)]))


def signatures(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = PERCENT, k: int = SHINGLE_WORDS) -> DataFrame:
    """(id, n, h1, h2, often, tokens): set size and fingerprint; one row of a slice of texts also carries its repeated tokens.

    ``tokens`` are the smallest hashes: the longest prefix and some more, in place
    of those that turn out to be frequent.
    """
    def start():
        def work(texts):
            sets = [shingle_set(t, k) for t in texts]
            prints = [_print_of(s) for s in sets]
            tokens, counts = np.unique(np.concatenate([np.zeros(0, np.uint64), *sets]), return_counts=True)
            many = counts >= BATCH_REPEATS
            often = [[{"token": int(t), "c": int(c)} for t, c in zip(tokens[many].view(np.int64), counts[many], strict=True)]]
            spare = [_prefix_length(len(s), percent) for s in sets]
            return {
                "n": [len(s) for s in sets], "h1": [int(p[0]) for p in prints], "h2": [int(p[1]) for p in prints],
                "often": (often + [None] * len(texts))[: len(texts)],
                "tokens": _list_array([s[: m + SPARE + m // 8] for s, m in zip(sets, spare, strict=True)]),
            }

        return work

    return map_texts(docs, start, "n long, h1 long, h2 long, often array<struct<token:long,c:long>>, tokens array<long>", id_col, text_col)


def frequent_tokens(marked: DataFrame) -> np.ndarray:
    """Up to MOST_FREQUENT tokens that many documents hold, sorted.  They only steer the order of tokens."""
    rows = (
        marked.where(F.col("often").isNotNull()).select(F.explode("often").alias("o")).groupBy("o.token").agg(F.sum("o.c").alias("c"))
        .where(F.col("c") >= FREQUENT).orderBy(F.desc("c"), "token").limit(MOST_FREQUENT).select("token").toPandas()
    )
    return np.sort(rows["token"].to_numpy(np.int64).view(np.uint64))


def _is_late(tokens: np.ndarray, late: np.ndarray) -> np.ndarray:
    if not len(late):
        return np.zeros(len(tokens), dtype=bool)
    return late[np.minimum(np.searchsorted(late, tokens), len(late) - 1)] == tokens


def trimmed(marked: DataFrame, frequent: np.ndarray, percent: int = PERCENT) -> DataFrame:
    """(d, n, tokens, enough) from (d, n, tokens): the longest prefix without frequent tokens.

    A document whose stored tokens do not suffice is marked; its text must be read again.
    """
    held = marked.sparkSession.sparkContext.broadcast(frequent)
    kind = marked.schema["d"].dataType.simpleString()

    def run(batches):
        for b in batches:
            sizes, lists = b.column(1).to_pylist(), b.column(2)
            flat = lists.flatten().to_numpy(zero_copy_only=False).view(np.uint64)
            ends = np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))]).astype(int)
            rare, cut, enough = ~_is_late(flat, held.value), [], []
            for i, n in enumerate(sizes):
                here, most = slice(ends[i], ends[i + 1]), _prefix_length(n, percent)
                few = flat[here][rare[here]]
                whole = ends[i + 1] - ends[i] == n  # frequent tokens then follow the others
                cut.append((np.concatenate([few, flat[here][~rare[here]]]) if whole else few)[:most])
                enough.append(whole or len(few) >= most)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), _list_array(cut), pa.array(enough, pa.bool_())], names=["d", "n", "tokens", "enough"])

    return marked.select("d", "n", "tokens").mapInArrow(run, f"d {kind}, n long, tokens array<long>, enough boolean")


def prefixes(docs: DataFrame, frequent: np.ndarray, percent: int = PERCENT, k: int = SHINGLE_WORDS) -> DataFrame:
    """(d, n, tokens): the longest prefix that a document may pick, in the global order, from its text."""
    held = docs.sparkSession.sparkContext.broadcast(frequent)

    def start():
        def work(texts):
            sizes, cut = [], []
            for t in texts:
                s = shingle_set(t, k)
                is_late = _is_late(s, held.value)
                sizes.append(len(s))
                cut.append(np.concatenate([s[~is_late], s[is_late]])[: _prefix_length(len(s), percent)])
            return {"n": sizes, "tokens": _list_array(cut)}

        return work

    return map_texts(docs, start, "n long, tokens array<long>", "d")


def without(rows: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows whose d is not in the written table ``ids`` (d); only those that may be in it are shuffled."""
    maybe = bit_filter(ids)
    sure = rows.where(~maybe(F.col("d")))
    return sure.unionByName(rows.where(maybe(F.col("d"))).join(ids, "d", "left_anti").select(*rows.columns))


def prefix_postings(sets: DataFrame, percent: int = PERCENT) -> DataFrame:
    """(token, d, n, p, ell, lev, own): prefix tokens at place p, with the level at which each enters.

    ``sets``: (d, n, tokens) of class representatives.  ``own`` counts the document's
    longest-prefix tokens that no other holds.  Documents that no set of any size
    can be similar to are left out.
    """
    spread = sets.select("d", "n", F.posexplode("tokens").alias("p", "token"))
    # Written before the join: its shuffle is freed, and a token that very many hold is then split by the planner.
    shared = materialise(spread.groupBy("token").agg(F.count(F.lit(1)).alias("df")).where("df > 1"))
    placed = _placed(spread.join(shared, "token"), percent)
    out = materialise(placed)
    release(shared)
    return out


def _placed(kept: DataFrame, percent: int) -> DataFrame:
    least = owed(F.col("n"), percent)
    placed = kept.withColumn("lev", F.greatest(F.lit(1), F.col("p") + 1 - (F.col("n") - least)))
    # Estimated cost of each L: postings read, and pairs that can reach L matches.
    by_doc = Window.partitionBy("d")
    reads = [F.sum(F.when(F.col("lev") <= ell, F.col("df") - 1).otherwise(0)).over(by_doc) for ell in range(1, MOST_MATCHES + 1)]
    # A similar set shares L tokens of the L-prefix, at every L: a document with fewer that others hold has no partner.
    held = [F.sum((F.col("lev") <= ell).cast("long")).over(by_doc) for ell in range(1, MOST_MATCHES + 1)]
    hope = reduce(and_, (h >= F.least(F.lit(ell), least) for ell, h in enumerate(held, 1)))
    own = F.col("n") - least + F.least(F.lit(MOST_MATCHES), least) - F.element_at(F.array(*held), F.least(F.lit(MOST_MATCHES), least).cast("int"))
    costs = F.array(*[reads[ell - 1] * (1.0 + VERIFY_COST / ell) for ell in range(1, MOST_MATCHES + 1)])
    usable = F.slice(costs, 1, F.least(F.lit(MOST_MATCHES), F.greatest(F.lit(1), least.cast("int"))))
    priced = placed.select("token", "d", "n", "p", "lev", usable.alias("usable"), own.alias("own"), hope.alias("hope")).where("hope")
    return priced.withColumn("ell", F.array_position("usable", F.array_min("usable")).cast("int")).where("lev <= ell").select("token", "d", "n", "p", "ell", F.col("lev").cast("int").alias("lev"), "own")


def leader_pairs(postings: DataFrame, turn: int = 0, percent: int = PERCENT) -> DataFrame:
    """(a, b): each document with the leader, from another component, that it meets most often.

    ``postings`` carry the component c.  A list's first leader is the member with the
    fewest tokens of its own, as the text that others were copied from.  Later leaders come in an order that changes
    with the turn and is the same for all lists.
    """
    order = F.struct((F.xxhash64(F.lit(turn), "d") if turn else F.col("own")).alias("o"), "d", "n", "c")
    leaders = materialise(postings.groupBy("token").agg(F.min(order).alias("m"), F.count(F.lit(1)).alias("k")).where("k > 1").select("token", "m"))
    # A leader is met on a part of the common tokens only, so the bar here is one hit.
    met = postings.join(leaders, "token").where((F.col("c") != F.col("m.c")) & (100 * F.least("n", "m.n") >= percent * F.greatest("n", "m.n")))
    best = met.groupBy(F.col("m.d").alias("a"), F.col("d").alias("b")).agg(F.count(F.lit(1)).alias("hits"))
    pairs = best.groupBy("b").agg(F.max(F.struct(F.col("hits"), F.bitwise_not("a").alias("na"))).alias("m")).select(F.bitwise_not("m.na").alias("a"), "b")
    made = materialise(pairs)
    release(leaders)
    return made


def _size_class(n: Column) -> Column:
    return F.floor(F.log(n.cast("double")) / math.log(CLASS_RATIO)).cast("int")


def _class_bit(g: Column) -> Column:
    return F.pmod(g, F.lit(CLASS_BITS)).cast("int")


def labelled(postings: DataFrame, components: DataFrame) -> DataFrame:
    """Postings of the lists whose members are in several components, with the component c and the list's members k, range of sizes and mask of size classes."""
    named = postings.join(components, postings["d"] == components["v"], "left").select("token", "d", "n", "p", "ell", "lev", "own", F.coalesce("component", "d").alias("c"))
    in_list = named.withColumn("bit", F.call_function("shiftleft", F.lit(1).cast("long"), _class_bit(_size_class(F.col("n"))))).groupBy("token")
    spans = [F.min("c").alias("lo"), F.max("c").alias("hi"), F.min("n").alias("n_lo"), F.max("n").alias("n_hi"), F.count(F.lit(1)).alias("k"), F.bit_or("bit").alias("classes")]
    open_ = materialise(in_list.agg(*spans).where("lo < hi").drop("lo", "hi"))
    out = materialise(named.join(open_, "token"))
    release(open_)
    return out


def pairs_ahead(live: DataFrame) -> tuple[int, int]:
    """Pairs across components that the lists would yield, and postings, counted exactly."""
    shares = live.groupBy("token", "c").agg(F.count(F.lit(1)).alias("k")).groupBy("token").agg(F.sum("k").alias("n"), F.sum(F.col("k") * F.col("k")).alias("sq"))
    got = shares.agg(F.sum(F.expr("(n * n - sq) div 2")), F.sum("n")).first()
    return int(got[0] or 0), int(got[1] or 0)


def leader_links(postings: DataFrame, texts: DataFrame, percent: int = PERCENT, k: int = SHINGLE_WORDS) -> tuple[DataFrame, DataFrame]:
    """Links found by comparing documents with list leaders, turn by turn, and the postings that stay open.

    A turn reads each posting once.  Turns go on while the pairs that are left far
    outnumber the postings and the last turn helped; what they miss is found by
    ``cross_pairs``, so their number has no effect on the result.
    """
    live, links, ahead = postings.withColumn("c", F.col("d")), None, math.inf
    for turn in range(MOST_TURNS):
        pairs = leader_pairs(live, turn, percent)
        found = verified(pairs, texts, percent, k)
        earlier, links = links, materialise(found if links is None else links.unionByName(found))
        release(pairs)
        if turn:
            release(earlier, live)
        live = labelled(postings, connected_components(links))
        before, (ahead, rows) = ahead, pairs_ahead(live)
        if ahead <= PAIRS_PER_POSTING * rows or (turn and ahead > 0.9 * before):
            break
    return links, live


def with_alone(live: DataFrame, texts: DataFrame, k: int = SHINGLE_WORDS) -> DataFrame:
    """``live`` with the column alone: of a crowded document, its tokens that no other crowded one holds; else null.

    A document is crowded if its lists hold many members for the size of its set, as
    those of texts copied with many changes do.  Two crowded ones share no token that
    is alone, which tells most such copies apart without a look at the pair.  The
    members that all other documents meet are at most their tokens in number.
    """
    crowd = materialise(live.groupBy("d").agg(F.sum(F.col("k") - 1).alias("met"), F.min("n").alias("n")).where(F.col("met") > CROWDED * F.col("n")).select("d"))

    def start():
        return lambda some: {"tokens": _list_array([shingle_set(t, k) for t in some])}

    # A document that the filter lets through by chance only makes fewer tokens alone.
    whole = map_texts(texts.where(bit_filter(crowd)(F.col("d"))), start, "tokens array<long>", "d")
    single = whole.select("d", F.explode("tokens").alias("token")).groupBy("token").agg(F.count(F.lit(1)).alias("df"), F.min("d").alias("d")).where("df = 1")
    told = materialise(crowd.join(single.groupBy("d").agg(F.count(F.lit(1)).alias("alone")), "d", "left").select("d", F.coalesce("alone", F.lit(0)).alias("alone")))
    out = materialise(live.join(told, "d", "left").select(*live.columns, "alone"))
    release(crowd, told)
    return out


def _with_hope(live: DataFrame, larger_partner: bool, percent: int) -> DataFrame:
    """Postings once per size class of the partner sought, without those that no partner can be similar to.

    Similar sets of n and m tokens share w = percent (n + m) / (100 + percent), so
    their first ell common tokens are among the first n - w + ell of each.  Taking
    the least m of the class makes the prefix shorter than one for any partner.  A
    document that has fewer than ell open postings there, at every ell up to its
    own, cannot have a partner in the class; neither can one with too many tokens
    of its own.  Lists without a member in the class are passed over.
    """
    g, n = F.col("g"), F.col("n")
    steps = math.floor(math.log(100 / percent) / math.log(CLASS_RATIO)) + 1
    reach = (F.col("g_hi") - g) if larger_partner else (g - F.col("g_lo"))
    spread = live.withColumn("step", F.explode(F.sequence(F.lit(0), F.least(F.lit(steps), reach))))
    partner = g + F.col("step") if larger_partner else g - F.col("step")
    there = F.call_function("getbit", "classes", _class_bit(partner)) == 1
    spread = spread.where(there & ((F.col("step") > 0) | (F.col("k") > 2) | (F.col("g_lo") == F.col("g_hi"))))
    least = F.greatest(F.floor(F.pow(F.lit(CLASS_RATIO), partner) * (1 - 1e-9)).cast("long"), owed(n, percent))
    shared = F.floor((percent * (n + least) + 99 + percent) / (100 + percent)).cast("long")
    tight = spread.where((100 * n >= percent * least) & (shared <= n - F.col("own"))).withColumn("lev", F.greatest(F.lit(1), F.col("p") + 1 - (n - shared)).cast("int")).where("lev <= ell")
    one = Window.partitionBy("d", "step")
    held = [F.sum((F.col("lev") <= ell).cast("int")).over(one) for ell in range(1, MOST_MATCHES + 1)]
    most = F.greatest(F.lit(0), *[F.when((F.col("ell") >= ell) & (held[ell - 1] >= ell), ell).otherwise(0) for ell in range(1, MOST_MATCHES + 1)])
    key = g if larger_partner else partner
    return tight.withColumn("most", most).where("lev <= most").select("token", key.alias("small"), "step", "d", "n", "p", "ell", "lev", "c", "alone")


def cross_pairs(live: DataFrame, percent: int = PERCENT) -> DataFrame:
    """(a, b) of every pair in different components that shares enough prefix tokens and has not too many others.

    ``live``: postings of ``with_alone``.
    """
    ends = {at: _size_class(F.col("n" + at)) for at in ("", "_lo", "_hi")}
    classed = live.withColumns({"g" + at: g for at, g in ends.items()}).withColumn("ell", F.least("ell", F.lit(MOST_CROSS)))
    side = lambda df, at: df.select("token", "small", "step", F.col("d").alias(at), F.col("n").alias("n" + at), F.col("p").alias("p" + at), F.col("lev").alias("l" + at), F.col("ell").alias("e" + at), F.col("c").alias("c" + at), F.col("alone").alias("s" + at))
    x, y = side(_with_hope(classed, True, percent), "a"), side(_with_hope(classed, False, percent), "b")
    met = x.join(y, ["token", "small", "step"]).where((F.col("ca") != F.col("cb")) & ((F.col("step") > 0) | (F.col("ca") < F.col("cb"))))
    ell = F.least("ea", "eb")
    # Common tokens before and after this one are no more than the shorter of the two stretches.
    room = F.least("pa", "pb") + F.least(F.col("na") - F.col("pa"), F.col("nb") - F.col("pb"))
    near = ((100 + percent) * room >= percent * (F.col("na") + F.col("nb"))) & (100 * F.least("na", "nb") >= percent * F.greatest("na", "nb"))
    # Two crowded sets share at most what is not alone in either.
    left = F.least(F.col("na") - F.col("sa"), F.col("nb") - F.col("sb"))
    told = F.col("sa").isNotNull() & F.col("sb").isNotNull() & ((100 + percent) * left < percent * (F.col("na") + F.col("nb")))
    fits = met.where((F.col("la") <= ell) & (F.col("lb") <= ell) & near & ~told)
    return fits.groupBy("a", "b").agg(F.count(F.lit(1)).alias("hits"), F.min(ell).alias("ell")).where("hits >= ell").select("a", "b")


def verified(pairs: DataFrame, texts: DataFrame, percent: int = PERCENT, k: int = SHINGLE_WORDS) -> DataFrame:
    """The pairs (a, b) of a written table whose full shingle sets are similar enough.

    Texts are read anew each time; those without a pair stay out of the shuffles.
    """
    side = lambda at: texts.where(bit_filter(pairs.select(at))(F.col("d"))).select(F.col("d").alias(at), F.col("text").alias("t" + at))
    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "ta", "tb")

    def run(batches):
        for batch in (part for whole in batches for part in slices(whole, 3)):
            last, keep = (None, None), []
            cache: dict = {}
            for a, b, ta, tb in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if last[0] != a:
                    last = (a, shingle_set(ta, k))
                if b not in cache:
                    cache = {b: shingle_set(tb, k)}
                x, y = last[1], cache[b]
                shared = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * shared >= percent * (len(x) + len(y) - shared))
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(keep, pa.bool_())), batch.column(1).filter(pa.array(keep, pa.bool_()))], names=["a", "b"])

    return both.mapInArrow(run, pairs.select("a", "b").schema)


def similar_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = PERCENT, k: int = SHINGLE_WORDS) -> DataFrame:
    """(id, n_shingles, component_id) for every row of ``docs``."""
    marked = materialise(signatures(docs, id_col, text_col, percent, k).withColumnRenamed(id_col, "d"))
    source = docs.select(docs[id_col].alias("d"), F.coalesce(docs[text_col].cast("string"), F.lit("")).alias("text")).where(F.col("d").isNotNull())
    sets = marked.where(F.col("d").isNotNull() & (F.col("n") > 0)).select("d", "n", "h1", "h2", "tokens")
    aliases = None
    if not sets.groupBy("d").count().where("count > 1").isEmpty():
        # An id with several rows: its further texts stand as vertices of their own, tied to the id.
        own = sets.groupBy("d").agg(F.min("h1").alias("own"))
        named = sets.join(own, "d").withColumn("alias", F.when(F.col("h1") == F.col("own"), F.col("d")).otherwise(-2 - F.pmod(F.xxhash64("d", "h1"), F.lit((1 << 62) - 1))))
        named = materialise(named.dropDuplicates(["alias"]))
        aliases = materialise(named.where(F.col("alias") != F.col("d")).select("d", "alias", "h1"))
        sets = named.select(F.col("alias").alias("d"), "n", "h1", "h2", "tokens")
        texts_of = source.withColumn("h1", _first_print(k)(F.col("text"))).join(aliases, ["d", "h1"], "left")
        source = materialise(texts_of.select(F.coalesce("alias", "d").alias("d"), "text").dropDuplicates(["d"]))
    by_set = sets.groupBy("h1", "h2").agg(F.min("d").alias("rep"), F.count(F.lit(1)).alias("c"))
    # Copies hang on the smallest id of their class; an id with several texts joins its classes.
    copies = sets.select("d", "h1", "h2").join(by_set.where("c > 1"), ["h1", "h2"]).where("d > rep").select(F.col("rep").alias("a"), F.col("d").alias("b"))
    copies = materialise(copies)
    frequent = frequent_tokens(marked)
    stored = materialise(trimmed(without(sets, copies.select(F.col("b").alias("d"))), frequent, percent))
    short = stored.where(~F.col("enough")).select("d")
    again = prefixes(source.where(bit_filter(short)(F.col("d"))), frequent, percent, k).join(short, "d", "left_semi")
    cut = materialise(stored.where("enough").select("d", "n", "tokens").unionByName(again.select("d", "n", "tokens")))
    sizes = materialise(marked.select("d", "n"))
    release(stored, marked, *([] if aliases is None else [named]))
    postings = prefix_postings(cut, percent)
    release(cut)
    with_list = materialise(postings.groupBy("token").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("token"))
    live = materialise(postings.join(with_list, "token", "left_semi"))
    release(postings, with_list)
    star, open_lists = leader_links(live, source, percent, k)
    release(live)
    told = with_alone(open_lists, source, k)
    release(open_lists)
    pairs = materialise(cross_pairs(told, percent))
    release(told)
    rest = materialise(verified(pairs, source, percent, k))
    release(pairs)
    links = star.unionByName(rest).unionByName(copies)
    if aliases is not None:
        links = links.unionByName(aliases.select(F.col("d").alias("a"), F.col("alias").alias("b")))
    found = connected_components(links)
    if aliases is not None:  # labels are real ids only
        real = found.join(aliases.select("alias"), F.col("v") == F.col("alias"), "left_anti")
        found = real.join(real.groupBy("component").agg(F.min("v").alias("least")), "component").select("v", F.col("least").alias("component"))
    out = sizes.select("d", F.col("n").alias("n_shingles")).join(found, F.col("d") == F.col("v"), "left")
    return out.select(F.col("d").alias(id_col), "n_shingles", F.coalesce("component", "d").alias("component_id"))


def op10_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_components(table(spark, sf_dir, "documents").select("doc_id", "text"))
