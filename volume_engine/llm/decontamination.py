"""Benchmark decontamination by SimHash windows, in DataFrame expressions only.

Words are lower-cased letters and digits.  A window is a run of as many words of a document as the
benchmark item has (cut off at the document's end).  A window counts as a leak when its five-word
shingles, weighted by how often they occur, have a Jaccard similarity of at least ``percent`` with
the item's; an item of one to four words is a single shingle and has to occur as it is.

Windows begin wherever a shingle of some item of that length occurs in a document.  Other windows
can be left out: a window that shares no shingle has similarity 0, and moving a window's start to
its first shared shingle never lowers the similarity.  Which items a window is compared with is up to
its 64-bit SimHash alone: it is cut into 8 blocks, and an index of the items' blocks with all values
within Hamming distance 2 finds every item of that length whose fingerprint is within 23 bits (8
blocks cannot all differ by 3 bits or more).  The exact similarity then decides.  Equal windows are
fingerprinted and compared once, however many documents hold them.

Defined results: null and blank texts and items have no words and never match; a text of one to four
words matches only an item of the same words or one that occurs in it; repeated rows of a document give one
result row per document and item (the best window, the first one on ties); an empty documents or
benchmark table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise, scan_bytes, word_array

WIDTH = 5
BLOCKS = 8
NEAR = 2  # bits within a block; 8 * 3 - 1 = 23 bits in all are guaranteed
RADIUS = BLOCKS * (NEAR + 1) - 1
MOST_BROADCAST = 1_000_000  # rows that are sent everywhere; more are joined by shuffle
MOST_BYTES = 32 << 20  # and the bytes of their files
LANE = 21  # bits of a counter, three to a long: windows of up to two million words


def bounded(df: DataFrame) -> DataFrame:
    """``df`` (already written) with a broadcast hint if its rows and its files are few enough to be sent everywhere."""
    return F.broadcast(df) if scan_bytes(df) <= MOST_BYTES and df.count() <= MOST_BROADCAST else df


def normal_words(text: str) -> Column:
    return word_array(F.regexp_replace(F.lower(F.col(text)), "[^\\p{L}\\p{N} \\t-\\r]+", ""))


def shingles(words: str) -> str:
    """SQL: hashes of the five-word runs of the array ``words``; of all its words if there are fewer."""
    run = ", ".join(f"{words}[i + {k}]" for k in range(WIDTH))
    return (
        f"case when size({words}) >= {WIDTH} then transform(sequence(0, size({words}) - {WIDTH}), i -> xxhash64({run}))"
        f" when size({words}) > 0 then array(xxhash64(size({words}), array_join({words}, ' '))) else cast(array() as array<bigint>) end"
    )


def simhash(words: str) -> str:
    """SQL: 64-bit SimHash of the array ``words``, each word weighted by its occurrences; a bit is set where most words have it."""
    hashes = f"transform({words}, w -> xxhash64(w))"
    three = f"(shiftright(x, 3 * k) & 1L) | shiftleft(shiftright(x, 3 * k) & 2L, {LANE - 1}) | shiftleft(shiftright(x, 3 * k) & 4L, {2 * LANE - 2})"
    lanes = f"transform(array({hashes}), h -> transform(sequence(0, 21), k -> aggregate(h, 0L, (a, x) -> a + ({three}))))[0]"
    set_bits = " | ".join(f"if(2 * (shiftright(a, {LANE * j}) & {(1 << LANE) - 1}L) > size({words}), shiftleft({1 << j}L, 3 * k), 0L)" for j in range(3))
    return f"aggregate(transform({lanes}, (a, k) -> {set_bits}), 0L, (p, q) -> p | q)"


def block_values(fingerprint: str) -> str:
    """SQL: the 8 blocks of a fingerprint, the block number in front (block * 256 + value)."""
    return f"transform(sequence(0, {BLOCKS - 1}), k -> k * 256 + cast(shiftright({fingerprint}, 8 * k) & 255 as int))"


def near_masks() -> list[int]:
    return [m for m in range(256) if m.bit_count() <= NEAR]


def weighted_shared(a: str, b: str) -> str:
    """SQL: sum of the smaller multiplicities of the elements of two arrays."""
    counted = f"aggregate(array_distinct({a}), 0, (s, x) -> s + least(size(filter({a}, y -> y = x)), size(filter({b}, y -> y = x))))"
    plain = f"size(array_distinct({a})) = size({a}) and size(array_distinct({b})) = size({b})"
    return f"if({plain}, size(array_intersect({a}, {b})), {counted})"


def short_shingles(words: str, width: int) -> str:
    """SQL: (place, hash) of every run of ``width`` words (fewer than five), hashed as an item of that many words is."""
    return f"if(size({words}) >= {width}, transform(sequence(0, size({words}) - {width}), i -> struct(i as at, xxhash64({width}, array_join(slice({words}, i + 1, {width}), ' ')) as shingle)), null)"


def leaks(docs: DataFrame, benchmark: DataFrame, percent: int = 75) -> DataFrame:
    """doc_id, item_id, start_word, n_words, shared, similarity and distance of every leak of ``benchmark`` (item_id, text) in ``docs`` (doc_id, text)."""
    docs = docs.select("doc_id", "text")
    items = benchmark.select("item_id", normal_words("text").alias("words")).filter("size(words) > 0")
    items = items.withColumns({"shingles": F.expr(shingles("words")), "length": F.size("words"), "print": F.expr(simhash("words"))}).drop("words")
    items = materialise(items, "leak-items")
    wanted = materialise(items.select("length", F.explode("shingles").alias("shingle")).distinct(), "leak-shingles")

    # where does a shingle of an item occur?
    texts = docs.select("doc_id", normal_words("text").alias("words"))
    # the outer form: the plain one would push a filter on the hashes below them and compute them per word
    placed = texts.select("doc_id", F.expr(shingles("words")).alias("shingles")).select("doc_id", F.posexplode_outer("shingles").alias("at", "shingle"))
    for width in sorted(r[0] for r in wanted.filter(f"length < {WIDTH}").select("length").distinct().collect()):  # four lengths at most
        few = texts.select("doc_id", F.explode_outer(F.expr(short_shingles("words", width))).alias("s"))
        placed = placed.unionByName(few.select("doc_id", "s.at", "s.shingle"))
    hits = placed.join(bounded(wanted), "shingle")
    places = materialise(hits.groupBy("doc_id", "length").agg(F.collect_set("at").alias("starts")), "leak-places")

    # item-sized windows there; the row of a text is not repeated for each of them
    cut = "transform(starts, s -> struct(s as start_word, slice(words, s + 1, length) as part))"
    found = docs.join(bounded(places), "doc_id").select("doc_id", "length", "starts", normal_words("text").alias("words"))
    windows = found.select("doc_id", "length", F.explode_outer(F.expr(cut)).alias("w")).select("doc_id", "length", "w.start_word", "w.part")
    windows = windows.filter("size(part) > 0").withColumns({"h": F.xxhash64("length", "part"), "g": F.xxhash64("part", F.lit(1), "length")})
    windows = materialise(windows, "leak-windows")
    same = ["length", "h", "g"]
    parts = windows.groupBy(*same).agg(F.first("part").alias("part"))
    parts = materialise(parts.select(*same, F.expr(simhash("part")).alias("print"), F.expr(shingles("part")).alias("parts")), "leak-parts")

    # candidates: items whose fingerprints lie within the radius
    index = items.select("item_id", "length", F.col("print").alias("item_print"), F.explode(F.expr(block_values("print"))).alias("value"))
    index = index.select("item_id", "length", "item_print", F.explode(F.array(*(F.col("value").bitwiseXOR(m) for m in near_masks()))).alias("value"))
    probes = parts.select(*same, "print", F.explode(F.expr(block_values("print"))).alias("value"))
    near = probes.join(bounded(materialise(index, "leak-index")), ["length", "value"]).withColumn("distance", F.bit_count(F.col("print").bitwiseXOR(F.col("item_print"))))
    near = near.filter(F.col("distance") <= RADIUS).select(*same, "item_id", "distance").distinct()

    # exact weighted similarity
    both = near.join(parts.select(*same, "parts"), same).join(bounded(items.select("item_id", "shingles")), "item_id")
    scored = both.withColumn("shared", F.expr(weighted_shared("parts", "shingles"))).withColumn("total", F.expr("size(parts) + size(shingles) - shared"))
    scored = scored.filter(100 * F.col("shared") >= percent * F.col("total")).withColumn("similarity", F.round(F.col("shared") / F.col("total"), 6))
    scored = materialise(scored.select(*same, "item_id", "shared", "similarity", "distance"), "leak-matches")
    best = F.struct(F.col("similarity"), (-F.col("start_word")).alias("earlier"), "length", "shared", "distance")
    out = windows.select("doc_id", *same, "start_word").join(bounded(scored), same).groupBy("doc_id", "item_id").agg(F.max(best).alias("best"))
    return out.select("doc_id", "item_id", (-F.col("best.earlier")).cast("long").alias("start_word"), F.col("best.length").cast("long").alias("n_words"), F.col("best.shared").cast("long").alias("shared"), "best.similarity", F.col("best.distance").cast("long").alias("distance"))


def op3_simhash_leaks(spark, sf_dir) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
