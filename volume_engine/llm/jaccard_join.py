"""Exact self-join of texts by the Jaccard similarity of their five-word shingles, with adaptive multi-match prefixes.

Texts with equal shingle sets are one class.  All sets are put into one global order, common
shingles last (their frequencies are estimated from every part of the corpus; the estimate steers
cost only).  Two sets with similarity t share at least ceil(t * n) shingles, so for any l they
share l of the first n - ceil(t * n) + l of either: a class with costly candidates takes a longer
prefix, a larger l, and a pair is verified only if it shares min(l, l') prefix shingles at
positions and sizes that still allow the similarity.

Components instead of pairs: in every prefix bucket the members are first compared with one of
them; what is linked then needs no further comparison.  Where few pairs of different components
remain (at most a fixed number per member) they are enumerated and verified; the other buckets are
cut into tiles: bitmaps tell which pairs are possible there; where those are few they are verified as
pairs, else the sets of the members concerned are sent to the tile, which verifies in place and
returns only a forest of links.  No pair is left out.

Defined results: null, empty and blank texts have no shingles and are linked with nothing; a text
with fewer than five words is one shingle; equal texts and repeated rows share a component; ties
go to the least doc_id; an empty table gives an empty result; extra columns are ignored.  Shingles
are told apart by 59-bit, classes by 64-bit fingerprints.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_scratch, materialise, mix64, release, scratch_mark, shingle_hashes, text_batches
from .components import connected

SLICE = 1 << 18  # bytes of text worked on at once
STRETCH = 1 << 20  # shingles among which the frequent ones are counted
CLASS_BITS = np.uint64(59)
HOT_SHINGLES = 1 << 18  # rows of the broadcast frequency table, whatever the corpus
SMALL_BUCKET = 64
TILE = 1024
BITMAP_LONGS = 64
PAIRS_PER_ROW = 32  # buckets with more pairs of different components than this per member are tiled
NEAR_PER_ROW = 1  # pairs per member of a tile that are verified as pairs; with more, the tile gets the members' sets
MOST_MATCHES = 4
MOST_BROADCAST = 1_000_000  # rows of two longs; more wanted classes are joined by shuffle


def shingle_sets(texts, width: int, limit: int = SLICE):
    """(first row, ids, sizes) per slice: the sorted distinct shingle ids of each text and their numbers."""
    for first, batch in text_batches(texts, limit):
        starts, ends, counts = batch.words()
        hashes, per_doc = shingle_hashes(batch.fingerprints(starts, ends), counts, width)
        owner = np.repeat(np.arange(batch.n), per_doc)
        ids, owner = by_owner(hashes >> np.uint64(5), owner)
        fresh = np.r_[True, (ids[1:] != ids[:-1]) | (owner[1:] != owner[:-1])] if len(ids) else np.zeros(0, bool)
        yield first, ids[fresh], np.bincount(owner[fresh], minlength=batch.n)


def by_owner(keys: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both arrays sorted by owner, then key."""
    order = np.argsort(keys)
    small = owner[order].astype(np.uint16) if len(owner) and owner[-1] < 1 << 16 else owner[order]
    order = order[np.argsort(small, kind="stable")]
    return keys[order], owner[order]


def class_ids(ids: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Fingerprint of each shingle set."""
    total = np.zeros(len(sizes), dtype=np.uint64)
    filled = sizes > 0
    if len(ids):
        total[filled] = np.add.reduceat(mix64(ids), (np.cumsum(sizes) - sizes)[filled])
    return mix64(total ^ mix64(sizes.astype(np.uint64)))


def _profile(width: int):
    """Class and size of every text, and shingles frequent within a stretch of texts."""

    def run(batches):
        empty = pa.nulls
        for batch in batches:
            pending: list[np.ndarray] = []
            for first, ids, sizes in shingle_sets(batch["text"], width):
                classes = class_ids(ids, sizes)
                n = len(sizes)
                yield pa.record_batch({"doc_id": batch["doc_id"].slice(first, n), "n": pa.array(sizes.astype(np.int32)), "cls": pa.array(classes.view(np.int64)), "token": empty(n, pa.int64())})
                _, at = np.unique(classes, return_index=True)
                once = np.zeros(n, dtype=bool)
                once[at] = True
                pending.append(ids[np.repeat(once, sizes)])
                if sum(map(len, pending)) > STRETCH:
                    yield from frequent(pending)
                    pending = []
            yield from frequent(pending)

    def frequent(pending):
        if pending and sum(map(len, pending)):
            tokens, counts = np.unique(np.concatenate(pending), return_counts=True)
            hot = counts >= 3
            n = int(hot.sum())
            yield pa.record_batch({"doc_id": pa.nulls(n, pa.int64()), "n": pa.array(counts[hot].astype(np.int32)), "cls": pa.nulls(n, pa.int64()), "token": pa.array(tokens[hot].astype(np.int64))})

    return run


def prefix_lengths(sizes: np.ndarray, percent: int, matches) -> np.ndarray:
    least = -(-sizes * percent // 100)
    return np.where(sizes > 0, sizes - least + np.minimum(matches, np.maximum(least, 1)), 0)


def _postings(width: int, percent: int, hot):
    """(token, cls, meta) of each class's adaptive prefix; meta packs size, position and matches."""

    def run(batches):
        hot_tokens, hot_counts = hot.value
        rank = np.floor(np.log2(hot_counts)).astype(np.uint64) if len(hot_counts) else np.zeros(0, np.uint64)
        seen: set[int] = set()
        for batch in batches:
            for _, ids, sizes in shingle_sets(batch["text"], width):
                classes = class_ids(ids, sizes)
                fresh = np.zeros(len(sizes), dtype=bool)
                for i, c in enumerate(classes.tolist()):
                    if sizes[i] and c not in seen:
                        seen.add(c)
                        fresh[i] = True
                keep = np.repeat(fresh, sizes)
                ids, sizes, classes = ids[keep], sizes[fresh], classes[fresh]
                if not len(ids):
                    continue
                owner = np.repeat(np.arange(len(sizes)), sizes)
                level = np.zeros(len(ids), dtype=np.uint64)
                cost = np.zeros(len(ids))
                if len(hot_tokens):
                    at = np.minimum(np.searchsorted(hot_tokens, ids), len(hot_tokens) - 1)
                    found = hot_tokens[at] == ids
                    level[found], cost[found] = rank[at[found]], hot_counts[at[found]]
                order = np.argsort((level << CLASS_BITS) | ids)
                order = order[np.argsort(owner[order].astype(np.uint16) if len(sizes) < 1 << 16 else owner[order], kind="stable")]
                ids, cost = ids[order], cost[order]
                place = np.arange(len(ids)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
                # estimated candidates of the plain prefix decide how many matches to ask for
                plain = place < np.repeat(prefix_lengths(sizes, percent, 1), sizes)
                expected = np.bincount(owner, np.where(plain, cost, 0), len(sizes))
                matches = np.clip(1 + np.floor(np.log2(1 + expected / 64)), 1, MOST_MATCHES).astype(np.int64)
                matches = np.minimum(matches, np.maximum(1, -(-sizes * percent // 100)))
                take = place < np.repeat(prefix_lengths(sizes, percent, matches), sizes)
                meta = (np.repeat(sizes, sizes) << 32) | (place << 3) | np.repeat(matches, sizes)
                yield pa.record_batch({"token": pa.array(ids[take].astype(np.int64)), "cls": pa.array(np.repeat(classes, sizes)[take].view(np.int64)), "meta": pa.array(meta[take].astype(np.int64))})

    return run


def _buckets(batches):
    """Rows sorted by (token, cls): keep tokens of two classes or more, with their first class and row number."""
    held = None  # an unfinished short run
    open_run = None  # (token, leader cls, leader meta, rows so far, last cls) of an unfinished long run

    def emit(t, c, m, lead_c, lead_m, number):
        return pa.record_batch({"token": pa.array(t), "cls": pa.array(c), "meta": pa.array(m), "lead": pa.array(lead_c), "lead_meta": pa.array(lead_m), "number": pa.array(number)})

    def close(t, c, m, final):
        nonlocal held, open_run
        fresh = np.r_[True, (t[1:] != t[:-1]) | (c[1:] != c[:-1])]
        if open_run and len(t) and t[0] == open_run[0] and c[0] == open_run[4]:
            fresh[0] = False
        t, c, m = t[fresh], c[fresh], m[fresh]
        held = None
        if not len(t):
            return
        if open_run and t[0] != open_run[0]:
            open_run = None
        begin = np.flatnonzero(np.r_[True, t[1:] != t[:-1]])
        size = np.diff(np.r_[begin, len(t)])
        lead_c, lead_m, number = np.repeat(c[begin], size), np.repeat(m[begin], size), np.arange(len(t)) - np.repeat(begin, size)
        take = np.repeat(size > 1, size)
        if open_run:
            n = size[0]
            lead_c[:n], lead_m[:n], take[:n] = open_run[1], open_run[2], True
            number[:n] += open_run[3]
            open_run = (open_run[0], open_run[1], open_run[2], open_run[3] + n, c[n - 1]) if len(size) == 1 else None
        if not final and open_run is None:
            last = begin[-1]
            if size[-1] > SMALL_BUCKET:
                open_run = (t[last], c[last], m[last], size[-1], c[-1])
            else:
                held = (t[last:], c[last:], m[last:])
                take[last:] = False
        if take.any():
            yield emit(t[take], c[take], m[take], lead_c[take], lead_m[take], number[take])

    for batch in batches:
        if batch.num_rows:
            t, c, m = (batch[k].to_numpy(zero_copy_only=False) for k in ("token", "cls", "meta"))
            if held is not None:
                t, c, m = (np.concatenate(x) for x in zip(held, (t, c, m), strict=True))
            yield from close(t, c, m, False)
    if held is not None:
        yield from close(*held, True)


def _sets(width: int, form: str):
    """The shingle set of each wanted class (``ids``), or its size and bitmap (``bits``)."""

    def run(batches):
        for batch in batches:
            wanted = batch["wanted"].to_numpy(zero_copy_only=False)
            for first, ids, sizes in shingle_sets(batch["text"], width):
                classes = class_ids(ids, sizes).view(np.int64)
                good = (classes == wanted[first : first + len(sizes)]) & (sizes > 0)
                ids, sizes = ids[np.repeat(good, sizes)].astype(np.int64), sizes[good]
                if form == "ids":
                    offsets = np.r_[0, np.cumsum(sizes)].astype(np.int32)
                    yield pa.record_batch({"cls": pa.array(classes[good]), "ids": pa.ListArray.from_arrays(pa.array(offsets), pa.array(ids))})
                    continue
                # at least four bits per shingle, in a power of two of longs
                width_of = BITMAP_LONGS << np.ceil(np.log2(np.maximum(sizes / (16 * BITMAP_LONGS), 1))).astype(np.int64)
                at = np.r_[0, np.cumsum(width_of)]
                bits = np.zeros(at[-1] * 64, dtype=bool)
                bits[np.repeat(at[:-1] * 64, sizes) + ids % np.repeat(width_of * 64, sizes)] = True
                longs, at = np.packbits(bits, bitorder="little").view("<i8"), at.astype(np.int32)
                yield pa.record_batch({"cls": pa.array(classes[good]), "n": pa.array(sizes.astype(np.int32)), "bits": pa.ListArray.from_arrays(pa.array(at), pa.array(longs))})

    return run


def _tile_candidates(percent: int):
    """The pairs (a, b) of different components of one tile pair that the bitmaps allow to be linked.

    Where they are more than a fixed number per member, the members concerned (cls) instead.
    """

    def run(table: pa.Table) -> pa.Table:
        left, right = table["i"][0].as_py(), table["j"][0].as_py()
        roots, tile, n = (table[k].to_numpy() for k in ("root", "tile", "n"))
        lists = table["bits"].combine_chunks()
        longs, edges = lists.flatten().to_numpy().view(np.uint64), lists.offsets.to_numpy()
        edges = edges - edges[0]
        bits = np.array([np.bitwise_or.reduce(longs[p:q].reshape(-1, BITMAP_LONGS)) for p, q in zip(edges[:-1], edges[1:], strict=True)])
        n = n.astype(np.int64)
        classes = table["cls"].to_numpy()
        found = np.zeros(len(n), dtype=bool)
        ends, held = [], 0
        for x in range(len(n)):
            other = (roots != roots[x]) & (100 * np.minimum(n, n[x]) >= percent * np.maximum(n, n[x]))
            if left != right:
                other &= tile != tile[x]
            at = np.flatnonzero(other)
            both = np.bitwise_count(bits[at] & bits[x]).sum(axis=1, dtype=np.int64)
            mine, theirs = np.bitwise_count(bits[x]).sum(dtype=np.int64) - both, np.bitwise_count(bits[at]).sum(axis=1, dtype=np.int64) - both
            most = np.minimum(n[x] - mine, n[at] - theirs)
            near = at[100 * most >= percent * (n[x] + n[at] - most)]
            found[near] = True
            found[x] |= len(near) > 0
            if held <= NEAR_PER_ROW * len(n):
                after = near[classes[near] > classes[x]]
                held += len(after)
                ends.append((np.full(len(after), classes[x]), classes[after]))
        if held <= NEAR_PER_ROW * len(n):
            a, b = (np.concatenate(e) for e in zip(*ends, strict=True))
            cls = pa.nulls(held, pa.int64())
        else:
            cls = pa.array(classes[found])
            a = b = pa.nulls(len(cls), pa.int64())
        same = {k: pa.array(np.full(len(cls), v), t) for k, v, t in (("token", table["token"][0].as_py(), pa.int64()), ("i", left, pa.int32()), ("j", right, pa.int32()))}
        return pa.table(same | {"cls": cls, "a": a, "b": b})

    return run


def _tile_links(percent: int):
    """Verify the pairs of one tile pair of a large bucket; return a forest of new links."""

    def run(table: pa.Table) -> pa.Table:
        left, right = table["i"][0].as_py(), table["j"][0].as_py()
        classes, roots, tile = (table[k].to_numpy() for k in ("cls", "root", "tile"))
        lists = table["ids"].combine_chunks()
        sizes = np.diff(lists.offsets.to_numpy())
        _, ids = np.unique(lists.flatten().to_numpy(), return_inverse=True)
        m = len(classes)
        owner = np.repeat(np.arange(m), sizes)
        order = np.argsort(ids, kind="stable")
        posting = owner[order]
        begin = np.searchsorted(ids[order], np.arange(ids.max() + 2 if len(ids) else 1))
        starts = np.cumsum(sizes) - sizes
        _, group, group_size = np.unique(roots, return_inverse=True, return_counts=True)
        parent = np.arange(len(group_size))

        def find(x: int) -> int:
            while parent[x] != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        links = []
        main = group_size.argmax()
        for x in range(m):
            if group[x] == main:  # pairs with the largest component are found from the other side
                continue
            own = ids[starts[x] : starts[x] + sizes[x]]
            length = begin[own + 1] - begin[own]
            at = np.repeat(begin[own] - (np.cumsum(length) - length), length) + np.arange(length.sum())
            shared = np.bincount(posting[at], minlength=m)
            linked = 100 * shared >= percent * (sizes[x] + sizes - shared)
            if left != right:
                linked &= tile != tile[x]
            for y in np.flatnonzero(linked).tolist():
                a, b = find(group[x]), find(group[y])
                if a != b:
                    parent[a] = b
                    links.append((classes[x], classes[y]))
        pairs = np.array(links, dtype=np.int64).reshape(-1, 2)
        return pa.table({"a": pairs[:, 0], "b": pairs[:, 1]})

    return run


def meta_parts(prefix: str = "", meta: str = "meta") -> list:
    m = F.col(meta)
    return [F.shiftright(m, 32).alias(f"{prefix}n"), F.shiftright(m.bitwiseAND(0xFFFFFFFF), 3).alias(f"{prefix}pos"), m.bitwiseAND(7).alias(f"{prefix}matches")]


def may_link(x: str, y: str, percent: int) -> str:
    """SQL: sizes and positions of a shared prefix shingle still allow the similarity."""
    need = f"(100 + {percent}) * (least({x}n - {x}pos, {y}n - {y}pos) + least({x}matches, {y}matches) - 1) >= {percent} * ({x}n + {y}n)"
    return f"100 * least({x}n, {y}n) >= {percent} * greatest({x}n, {y}n) and {need}"


def likely_pairs(pairs: DataFrame, bitmaps: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose bitmaps (cls, n, bits) leave the similarity possible.

    A bit that only one of two sets has stands for a shingle the other lacks, so the bitmaps, a
    tenth of the sets' size, bound the overlap; only pairs that they allow move sets.
    """

    def side(k: str) -> DataFrame:
        return bitmaps.select(F.col("cls").alias(k), F.col("n").alias(f"{k}_n"), F.col("bits").alias(f"{k}_bits"))

    rough = pairs.select("a", "b").join(side("a"), "a").join(side("b"), "b")
    # sizes within the similarity's ratio differ by one doubling of the bitmap at most: the halves of the longer one fold
    fold = "if(size({0}_bits) > size({1}_bits), zip_with(slice({0}_bits, 1, size({1}_bits)), slice({0}_bits, size({1}_bits) + 1, size({1}_bits)), (p, q) -> p | q), {0}_bits)"
    rough = rough.withColumns({f"{x}_bits": F.expr(fold.format(x, y)) for x, y in ("ab", "ba")})
    lacks = "aggregate(zip_with({0}_bits, {1}_bits, (p, q) -> bit_count(p & ~q)), 0, (s, x) -> s + x)"
    most = F.least(F.expr("a_n - " + lacks.format("a", "b")), F.expr("b_n - " + lacks.format("b", "a")))
    rough = rough.select("a", "b", "a_n", "b_n", most.alias("most"))
    return rough.filter(f"100 * most >= {percent} * (a_n + b_n - most)").select("a", "b")


def verified(likely: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets (cls, ids) reach the similarity."""
    a, b = (sets.select(F.col("cls").alias(k), F.col("ids").alias(f"{k}_ids")) for k in "ab")
    both = likely.join(a, "a").join(b, "b").withColumn("shared", F.size(F.array_intersect("a_ids", "b_ids")))
    return both.filter(f"100 * shared >= {percent} * (size(a_ids) + size(b_ids) - shared)").select("a", "b")


def link_components(docs: DataFrame, percent: int = 75, width: int = 5) -> DataFrame:
    """doc_id, n_shingles and component_id (least doc_id linked, itself included) of every row of ``docs`` (doc_id, text)."""
    spark = docs.sparkSession
    docs = docs.select("doc_id", "text")
    profile = materialise(docs.mapInArrow(_profile(width), "doc_id long, n int, cls long, token long"), "jaccard-profile")
    hot = profile.filter("token is not null").groupBy("token").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "token").limit(HOT_SHINGLES).toPandas().sort_values("token")
    table = spark.sparkContext.broadcast((hot.token.to_numpy().astype(np.uint64), hot.n.to_numpy(float)))
    classes = profile.filter("token is null and n > 0")

    postings = docs.select("text").mapInArrow(_postings(width, percent, table), "token long, cls long, meta long")
    bucket_schema = "token long, cls long, meta long, lead long, lead_meta long, number long"
    buckets = materialise(postings.repartition("token").sortWithinPartitions("token", "cls").mapInArrow(_buckets, bucket_schema), "jaccard-buckets")
    release(spark)

    firsts = materialise(classes.groupBy("cls").agg(F.min("doc_id").alias("first_doc")), "jaccard-classes")

    schemas = {"bits": "cls long, n int, bits array<long>", "ids": "cls long, ids array<long>"}

    def read_off(wanted: DataFrame, form: str) -> DataFrame:
        """Bitmaps or sets of the wanted classes, each made from the text of one member; a repeated row may repeat its class."""
        wanted = materialise(wanted.select("cls").distinct().join(firsts, "cls").select(F.col("first_doc").alias("doc_id"), F.col("cls").alias("wanted")), "jaccard-wanted")
        few = wanted.count() <= MOST_BROADCAST
        found = docs.join(F.broadcast(wanted) if few else wanted, "doc_id").select("text", "wanted")
        return materialise(found.mapInArrow(_sets(width, form), schemas[form]), f"jaccard-{form}")

    def of_pairs(pairs: DataFrame) -> DataFrame:
        return pairs.select(F.col("a").alias("cls")).unionByName(pairs.select(F.col("b").alias("cls")))

    # 1. every member of a bucket against the bucket's first class
    star = buckets.filter("cls != lead").select(F.col("lead").alias("a"), F.col("cls").alias("b"), *meta_parts("x_", "lead_meta"), *meta_parts("y_"))
    star = star.filter(may_link("x_", "y_", percent)).groupBy("a", "b").agg(F.count("*").alias("k"), F.first(F.expr("least(x_matches, y_matches)")).alias("least_k"))
    begin = scratch_mark()
    star = materialise(star.filter("k >= least_k").select("a", "b"), "jaccard-star-pairs")
    release(spark)
    likely = materialise(likely_pairs(star, read_off(of_pairs(star), "bits"), percent), "jaccard-star-likely")
    links = materialise(verified(likely, read_off(of_pairs(likely), "ids"), percent), "jaccard-star-links")
    roots = connected(links, "jaccard-star")
    end = scratch_mark()
    roots = materialise(roots, "jaccard-star-roots").withColumnRenamed("node", "cls")
    drop_scratch(spark, begin, end)
    release(spark)

    def rooted(df: DataFrame) -> DataFrame:
        return df.join(roots, "cls", "left").withColumn("root", F.coalesce("root", "cls"))

    rows = materialise(rooted(buckets.select("token", "cls", F.floor(F.col("number") / TILE).cast("int").alias("tile"), *meta_parts())), "jaccard-rows")
    groups = rows.groupBy("token", "root").agg(F.count("*").alias("k"), F.max("tile").alias("tile"))
    shape = groups.groupBy("token").agg(F.sum("k").alias("m"), F.sum(F.col("k") * F.col("k")).alias("sq"), F.max_by("root", F.struct("k", "root")).alias("main"), F.max("tile").alias("tiles"))
    shape = materialise(shape.filter("m * m > sq").withColumn("few", F.expr(f"(m * m - sq) <= 2 * {PAIRS_PER_ROW} * m")), "jaccard-shape")

    # 2. buckets with few pairs of different components: enumerate them, from the members outside the main component
    here = rows.join(shape.filter("few").select("token", "main"), "token")
    x, y = (here.select("token", "main", *(F.col(c).alias(f"{k}_{c}") for c in ("cls", "root", "n", "pos", "matches"))) for k in ("x", "y"))
    pairs = x.filter("x_root != main").join(y.drop("main"), "token").filter(f"x_root != y_root and (y_root = main or x_cls < y_cls) and {may_link('x_', 'y_', percent)}")
    ends = (F.least("x_cls", "y_cls").alias("a"), F.greatest("x_cls", "y_cls").alias("b"))
    pairs = pairs.groupBy(*ends).agg(F.count("*").alias("k"), F.first(F.expr("least(x_matches, y_matches)")).alias("least_k"))
    pairs = materialise(pairs.filter("k >= least_k").select("a", "b"), "jaccard-pairs")

    # 3. the other buckets: tiles of them, verified where their sets are sent
    dealt = rows.select("token", "cls", "root", "tile", "n").join(shape.filter("not few").select("token", "tiles"), "token")
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), "tiles")))
    dealt = dealt.select("token", "cls", "root", "tile", "n", F.least("tile", "other").alias("i"), F.greatest("tile", "other").alias("j"))
    dealt = materialise(dealt, "jaccard-dealt")
    release(spark)
    bitmaps = read_off(of_pairs(pairs).unionByName(dealt.select("cls")), "bits")
    place = ["token", "i", "j"]
    near = dealt.drop("n").join(bitmaps, "cls").groupBy(*place).applyInArrow(_tile_candidates(percent), "token long, i int, j int, cls long, a long, b long")
    near = materialise(near, "jaccard-near")
    pairs = materialise(pairs.unionByName(near.filter("a is not null").select("a", "b")).distinct(), "jaccard-all-pairs")
    likely = materialise(likely_pairs(pairs, bitmaps, percent), "jaccard-likely")
    dealt = materialise(dealt.join(near.filter("cls is not null"), [*place, "cls"], "left_semi").drop("n"), "jaccard-tiled")
    release(spark)
    sets = read_off(of_pairs(likely).unionByName(dealt.select("cls")), "ids")
    more = verified(likely, sets, percent)
    tiles = dealt.join(sets, "cls").groupBy(*place).applyInArrow(_tile_links(percent), "a long, b long")

    late = materialise(more.unionByName(tiles), "jaccard-late-links")
    ends = late
    for side in ("a", "b"):
        ends = ends.join(roots.select(F.col("cls").alias(side), F.col("root").alias(f"{side}_root")), side, "left").withColumn(side, F.coalesce(f"{side}_root", side)).drop(f"{side}_root")
    joined = connected(ends, "jaccard-late").select(F.col("node").alias("root"), F.col("root").alias("last"))
    members = roots.unionByName(joined.select(F.col("root").alias("cls"), "root")).distinct()
    members = materialise(members.join(joined, "root", "left").select("cls", F.coalesce("last", "root").alias("root")), "jaccard-members")
    named = materialise(members.join(firsts, "cls"), "jaccard-named")
    least = named.groupBy("root").agg(F.min("first_doc").alias("component_id"))
    components = named.join(least, "root").groupBy("cls").agg(F.min("component_id").alias("component_id"))
    final = materialise(firsts.join(components, "cls", "left").select("cls", F.coalesce("component_id", "first_doc").alias("component_id")), "jaccard-final")
    rows = profile.filter("token is null").select("doc_id", F.col("n").cast("long").alias("n_shingles"), "cls")
    return rows.join(final, "cls", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def op5_jaccard_components(spark, sf_dir) -> DataFrame:
    return link_components(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
