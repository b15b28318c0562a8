"""Benchmark decontamination with SimHash windows, by DataFrame functions alone.

Documents are cut into words (lower case, letters and digits), and into windows as long as an item. A window can reach the
threshold only if enough of its places hold a shingle of an item of that length, and a running count of such places tells at
which starts they do; a window is laid at every such start, and nowhere else. Counts are lower bounds of the need, so no
window over the threshold is left out, whatever the order of its passages. A document of fewer words than the item is one
window, whole. Equal windows are one row. Each gets a 64-bit SimHash of its shingles, which is matched with the items of
the same length through blocks of bits: two fingerprints at most ``radius`` apart agree in one of ``radius + 1`` blocks at
least. What is within the radius is then judged exactly, word by word, on the shingles weighted by how often they occur.

A bit of two fingerprints differs with a probability of arccos(8/9) / pi = 0.151 at a similarity of just 0.8, so a radius
of 20 loses 0.0002 of the windows there and fewer above. For the same reason no block that every pair within the radius
must share can be wider than some bits: blocks choose among the items of one length, the running count does the pruning.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import storage

WIDTH, RADIUS = 5, 20
#: Up to so many benchmark shingles are tested inside the scan; beyond it the documents' shingles are joined with them.
MAX_INLINE = 50_000


def words(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), "")


def shingle_at(w: Column, i: Column, width: int = WIDTH) -> Column:
    """Name of the shingle of ``width`` words that begins at word ``i`` (from 0)."""
    return F.xxhash64(*[F.get(w, i + j) for j in range(width)])


def starts(w: Column, width: int = WIDTH) -> Column:
    """Places where a shingle begins; empty for fewer words."""
    return F.when(F.size(w) >= width, F.sequence(F.lit(0), F.size(w) - width)).otherwise(F.array().cast("array<int>"))


def shingles(w: Column, width: int = WIDTH) -> Column:
    """Names of all shingles, repeats included; ``w`` must be a column or a lambda variable, not an expression."""
    return F.transform(starts(w, width), lambda i: shingle_at(w, i, width))


def simhash(names: Column) -> Column:
    """Bit b is set if more than half of the names have it set: each shingle weighs as often as it occurs."""
    votes = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda b: F.struct(b.alias("b"), F.aggregate(names, F.lit(0), lambda a, x: a + F.getbit(x, b).cast("int")).alias("n")))
    return F.aggregate(votes, F.lit(0).cast("bigint"), lambda a, v: F.when(v["n"] * 2 > F.size(names), a.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), v["b"]))).otherwise(a))


def hamming_blocks(fingerprint: Column, radius: int = RADIUS) -> Column:
    """(block, bits) for each of ``radius + 1`` blocks; they cover all 64 bits."""
    cuts = [64 * i // (radius + 1) for i in range(radius + 2)]
    return F.array(*[F.struct(F.lit(i).alias("block"), F.call_function("shiftrightunsigned", fingerprint, F.lit(a)).bitwiseAND(F.lit((1 << (b - a)) - 1).cast("bigint")).alias("bits")) for i, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False))])


def shingle_texts(w: Column, width: int = WIDTH) -> Column:
    """All shingles as text, repeats included; words hold no spaces, so equal texts are equal shingles."""
    return F.transform(starts(w, width), lambda i: F.array_join(F.slice(w, i + 1, width), " "))


def shared_weight(a: Column, b: Column) -> Column:
    """Sum over shingles of the smaller of their two multiplicities."""
    times = lambda x, y: F.size(F.filter(x, lambda z: z == y))
    once = lambda x: F.size(F.array_distinct(x)) == F.size(x)
    many = F.aggregate(F.array_intersect(a, b), F.lit(0), lambda s, y: s + F.least(times(a, y), times(b, y)))
    return F.when(once(a) | once(b), F.size(F.array_intersect(a, b))).otherwise(many)


def item_shingles(benchmark: DataFrame, item: str, text: str) -> DataFrame:
    """(item_id, n, w, names, fingerprint): items of five words and more; shorter or null items take no part."""
    cut = benchmark.select(F.col(item).cast("bigint").alias("item_id"), words(F.col(text)).alias("w")).where(F.size("w") >= WIDTH)
    cut = cut.select("item_id", F.size("w").alias("n"), "w", F.explode(F.transform(F.array("w"), lambda w: shingles(w))).alias("names"))
    return cut.select("item_id", "n", "w", "names", simhash(F.col("names")).alias("fingerprint"))


def least_shared(a: Column, b: Column, num: int, den: int) -> Column:
    """Shingles that sets of ``a`` and ``b`` shingles must share to be ``num/den`` similar, rounded up."""
    return F.ceil((a + b) * num / (num + den) - 1e-9).cast("int")


def window_starts(places: Column, size: Column, n: Column, num: int, den: int) -> Column:
    """Every start of a window of ``n`` words, among ``size``, in which enough of the (ascending) ``places`` lie.

    Window by window in order of the place that it begins before: from the i-th place on, ``need`` places fit into a window if
    it starts early enough to hold the last of them; starts that an earlier place has given are not given again.
    """
    width, need = n - (WIDTH - 1), least_shared(n - (WIDTH - 1), n - (WIDTH - 1), num, den)
    low = lambda i: F.greatest(F.get(places, i + need - 1) - width + 1, F.coalesce(F.get(places, i - 1), F.lit(-1)) + 1, F.lit(0))
    high = lambda i: F.least(F.get(places, i), size - n)
    of = lambda i: F.when(low(i) <= high(i), F.sequence(low(i), high(i))).otherwise(F.array().cast("array<int>"))
    laid = F.when(F.size(places) >= need, F.flatten(F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), F.size(places) - need)), of))).otherwise(F.array().cast("array<int>"))
    whole = F.when(F.size(places) >= least_shared(size - (WIDTH - 1), n - (WIDTH - 1), num, den), F.array(F.lit(0))).otherwise(F.array().cast("array<int>"))
    return F.when(size < n, whole).otherwise(laid)


def contaminated(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", num: int = 4, den: int = 5, radius: int = RADIUS) -> DataFrame:
    """(key, item_id, shared, weight): each pair of a document and an item of which it holds a similar window.

    Similar: the weighted Jaccard similarity shared / weight of the window's and the item's shingles is ``num/den`` or more;
    of several windows the most similar counts. A document of fewer words than the item is
    its own window; only null texts and those of fewer than five words hold nothing. Rows of the same key, null among them,
    are one document. The number of pairs is at most that of items in documents; a text that very many documents
    have is judged once.
    """
    items = storage.materialize(item_shingles(benchmark, item, item_text), "items")
    seeds = storage.materialize(items.select("n", F.explode("names").alias("name")).groupBy("name", "n").agg(F.lit(1).alias("one")).drop("one"), "item-seeds")
    names = [r.name for r in seeds.select("name").distinct().limit(MAX_INLINE + 1).collect()]
    rows = docs.select(F.col(key).cast("bigint").alias("id"), F.col(text).alias("t"))
    least = items.agg(F.min("n")).first()[0]
    if least is None:
        return rows.where(F.lit(False)).select(F.col("id").alias(key), F.lit(0).cast("bigint").alias("item_id"), F.lit(0).alias("shared"), F.lit(0).alias("weight"))
    fewest = max(1, -(-(least - WIDTH + 1) * num // den))  # places that the smallest window similar to any item holds
    th = F.sha2(F.col("t"), 256).alias("th")
    if len(names) <= MAX_INLINE:  # generators keep the words from being cut again for every use of them
        found = lambda w: F.filter(starts(w), lambda i: shingle_at(w, i).isin(names))
        met = rows.select("id", "t", F.explode(F.filter(F.transform(F.array(words(F.col("t"))), lambda w: F.struct(w.alias("w"), found(w).alias("hits"))), lambda m: F.size(m["hits"]) >= fewest)).alias("m")).select("id", th, "m.w", "m.hits")
    else:  # places travel without the words, which are joined on again where there are enough
        named = rows.select("id", "t", th)
        every = named.groupBy("th").agg(F.first("t").alias("t")).select("th", F.explode(F.transform(F.array(words(F.col("t"))), lambda w: shingles(w))).alias("names")).select("th", F.posexplode("names").alias("p", "name"))
        hits = every.join(seeds.select("name").distinct(), "name", "left_semi").groupBy("th").agg(F.array_sort(F.collect_set("p")).alias("hits")).where(F.size("hits") >= fewest)
        met = named.join(hits, "th").select("id", "th", words(F.col("t")).alias("w"), "hits")
    met = storage.materialize(met, "texts-with-shingles")
    texts = met.groupBy("th").agg(F.first("w").alias("w"), F.first("hits").alias("hits"))
    held = texts.select("th", F.size("w").alias("size"), F.explode(F.transform("hits", lambda p: F.struct(p.alias("p"), shingle_at(F.col("w"), p).alias("name")))).alias("s")).select("th", "size", "s.p", "s.name")
    places = held.join(seeds, "name").groupBy("th", "n", "size").agg(F.array_sort(F.collect_set("p")).alias("places"))
    laid = places.select("th", "n", F.explode(window_starts(F.col("places"), F.col("size"), F.col("n"), num, den)).alias("start"))
    laid = laid.join(met.select("th", "w").dropDuplicates(["th"]), "th").select("th", "n", F.slice("w", F.col("start") + 1, F.col("n")).alias("window"))
    laid = storage.materialize(laid.withColumn("wk", F.sha2(F.concat_ws(" ", "window"), 256)).groupBy("th", "n", "wk").agg(F.first("window").alias("window")), "windows")
    distinct = laid.groupBy("n", "wk").agg(F.first("window").alias("window")).select("n", "wk", "window", F.explode(F.transform(F.array("window"), lambda w: shingles(w))).alias("names"))
    distinct = storage.materialize(distinct.select("n", "wk", "window", simhash(F.col("names")).alias("fingerprint")), "fingerprints")
    side = lambda df, *cols: df.select(*cols, "n", "fingerprint", F.inline(hamming_blocks(F.col("fingerprint"), radius)))
    other = side(items, "item_id").withColumnsRenamed({"n": "_n", "block": "_block", "bits": "_bits", "fingerprint": "_f"})
    close = (F.col("n") == F.col("_n")) & (F.col("block") == F.col("_block")) & (F.col("bits") == F.col("_bits")) & (F.bit_count(F.col("fingerprint").bitwiseXOR(F.col("_f"))) <= radius)
    near = side(distinct, "wk").join(other, close).groupBy("n", "wk", "item_id").agg(F.lit(1).alias("one")).drop("one")
    judged = near.join(distinct.select("n", "wk", "window"), ["n", "wk"]).join(items.select("item_id", F.col("w").alias("item_words")), "item_id")
    judged = judged.select("n", "wk", "item_id", F.explode(F.array(F.struct(shingle_texts(F.col("window")).alias("a"), shingle_texts(F.col("item_words")).alias("b")))).alias("s"))
    judged = judged.select("n", "wk", "item_id", shared_weight(F.col("s.a"), F.col("s.b")).alias("shared"), (F.size("s.a") + F.size("s.b")).alias("both"))
    judged = judged.where(F.col("shared") * den >= (F.col("both") - F.col("shared")) * num)
    best = laid.select("th", "n", "wk").join(judged, ["n", "wk"]).groupBy("th", "item_id").agg(F.max(F.struct((F.col("shared") / (F.col("both") - F.col("shared"))).alias("ratio"), "shared", (F.col("shared") - F.col("both")).alias("less"))).alias("best"))
    pairs = met.select("id", "th").join(best, "th").groupBy("id", "item_id").agg(F.max("best").alias("best"))
    return pairs.select(F.col("id").alias(key), "item_id", F.col("best.shared").alias("shared"), (-F.col("best.less")).alias("weight"))


def clean_documents(docs: DataFrame, benchmark: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of ``docs`` that hold no item."""
    (own,) = storage.fresh(docs, "_id")
    held = contaminated(docs, benchmark, key, text).select(F.col(key).alias(own)).distinct()
    return docs.join(held, F.col(key).cast("bigint").eqNullSafe(F.col(own)), "left_anti")
