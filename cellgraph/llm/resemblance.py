"""Documents of high resemblance: groups by the Jaccard similarity of their sets of word shingles, exact.

The near-duplicate stage of a corpus asks for a similarity of shingle sets, which fingerprints of 64 bits
can only estimate: at 0.8 too many pairs are lost under any bit limit that also prunes.  So what
SimHash and pigeonring leave (`drop_near_duplicates` goes by them first) is compared exactly: candidates
come from the sets themselves, by rare-first prefixes, and whole sets decide.  Shingles are cut and
hashed as for the fingerprints.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from cellgraph.algorithms.contraction import components
from cellgraph.llm.simhash import near_duplicates, shingles
from cellgraph.scratch import Scratch
from cellgraph.workers import lean


#: Prefixes are longer than one common shingle asks for by a ``SPARE``-th of the set.
SPARE = 16


def shingle_hashes(text: str | None, words: int, seed: int) -> np.ndarray:
    """Sorted hashes of the distinct shingles."""
    import xxhash

    digest = xxhash.xxh64_intdigest
    return np.unique(np.fromiter((digest(s, seed) for s in shingles(text, words)), dtype=np.uint64))


def common_shingles(docs: DataFrame, text_col: str, words: int, seed: int, at_least: int = 8, keep: int = 200_000, block: int = 2_000_000) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of frequent shingles, sorted, and their counts: what is repeated within blocks of texts, summed; the most frequent ``keep``.

    It only sets an order of shingles, in which frequent ones come last.  Any order gives the same
    links, so that counts may be low or missing.
    """

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def repeated(parts: list[np.ndarray]) -> pa.RecordBatch:
            found, n = np.unique(np.concatenate(parts), return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(found[n > 1].view(np.int64)), pa.array(n[n > 1])], names=["shingle", "n"])

        parts, size = [], 0
        for b in batches:
            for t in b.column(0):
                parts.append(shingle_hashes(t.as_py(), words, seed))
                size += len(parts[-1])
                if size > block:
                    yield repeated(parts)
                    parts, size = [], 0
        if parts:
            yield repeated(parts)

    counts = docs.select(text_col).mapInArrow(run, "shingle long, n long").groupBy("shingle").agg(F.sum("n").alias("n")).where(F.col("n") >= at_least)
    rows = counts.orderBy(F.desc("n"), "shingle").limit(keep).collect()
    found = np.array([r["shingle"] for r in rows], dtype=np.int64).view(np.uint64)
    order = np.argsort(found)
    return found[order], np.array([r["n"] for r in rows], dtype=np.int64)[order]


def rare_prefix(found: np.ndarray, common: tuple[np.ndarray, np.ndarray], similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """The first shingles, rare ones first, of which any other set of that similarity has one among its own first, the next ``n // SPARE``, and their counts; none if only an equal set has it."""
    n = len(found)
    least = math.ceil(similarity * n - 1e-9)
    weight = np.zeros(n, dtype=np.int64)
    if n == least and math.floor(n / similarity + 1e-9) == n:
        return found[:0], weight[:0]
    hashes, counts = common
    if len(hashes):
        at = np.minimum(np.searchsorted(hashes, found), len(hashes) - 1)
        weight = np.where(hashes[at] == found, counts[at], 0)
    head = np.argsort(weight, kind="stable")[: n - least + 1 + n // SPARE]
    return found[head], weight[head]


def shingle_prefixes(docs: DataFrame, id_col: str, text_col: str, similarity: float, words: int, seed: int, common: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """``(id, n, d0, d1, prefix, fresh, w)``: number of distinct shingles, a 128-bit digest of their set, its `rare_prefix`, how many of that are not in ``common``, and the count of its last one."""
    import xxhash

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                b = batch.slice(at, 500)
                sizes, fresh, last = (np.zeros(b.num_rows, dtype=np.int64) for _ in range(3))
                digests, prefixes = [], []
                for i, t in enumerate(b.column(1)):
                    found = shingle_hashes(t.as_py(), words, seed)
                    head, weight = rare_prefix(found, common, similarity)
                    sizes[i], fresh[i], last[i] = len(found), np.count_nonzero(weight == 0), weight[-1] if len(weight) else 0
                    digests.append(xxhash.xxh3_128_digest(found.tobytes()))
                    prefixes.append(head.view(np.int64))
                halves = np.frombuffer(b"".join(digests), dtype=np.int64).reshape(-1, 2)
                cols = [pa.array(sizes), *(pa.array(np.ascontiguousarray(halves[:, k])) for k in (0, 1)), pa.array(prefixes, pa.list_(pa.int64())), pa.array(fresh), pa.array(last)]
                yield pa.RecordBatch.from_arrays([b.column(0), *cols], names=["id", "n", "d0", "d1", "prefix", "fresh", "w"])

    return docs.select(F.col(id_col).cast("long").alias("id"), text_col).mapInArrow(run, "id long, n long, d0 long, d1 long, prefix array<bigint>, fresh long, w long")


def shingle_sets(docs: DataFrame, ids: DataFrame, id_col: str, text_col: str, words: int, seed: int) -> DataFrame:
    """``(id, s)``: the sorted distinct shingle hashes of the rows whose id is in ``ids(id)``, equal rows once."""
    import xxhash

    @lean
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        digest = xxhash.xxh64_intdigest
        for b in batches:
            for at in range(0, b.num_rows, 500):
                part = b.slice(at, 500)
                sets = [np.unique(np.fromiter((digest(x, seed) for x in shingles(t.as_py(), words)), dtype=np.uint64)).view(np.int64) for t in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sets, pa.list_(pa.int64()))], names=["id", "s"])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).join(ids, "id", "left_semi")
    once = rows.groupBy("id", F.xxhash64("text"), F.xxhash64(F.lit(1), "text")).agg(F.first("text").alias("text"))
    return once.select("id", "text").mapInArrow(run, "id long, s array<bigint>")


def verified_pairs(doubtful: DataFrame, docs: DataFrame, id_col: str, text_col: str, similarity: float, words: int, seed: int, scratch: Scratch) -> DataFrame:
    """The pairs ``(a, b)`` of ``doubtful`` whose shingle sets have that Jaccard similarity, counted from the whole texts.

    ``b`` is joined first: a group's many pairs share their ``a``, whose set then stands on the single-row side.
    """
    ids = scratch.save(doubtful.select(F.explode(F.array("a", "b")).alias("id")).distinct())
    sets = scratch.save(shingle_sets(docs, ids, id_col, text_col, words, seed))
    held = doubtful.join(sets.select(F.col("id").alias("b"), F.col("s").alias("sb")), "b")
    held = held.join(sets.select(F.col("id").alias("a"), F.col("s").alias("sa")), "a")
    both, total = F.size(F.array_intersect("sa", "sb")), F.size("sa") + F.size("sb")
    links = scratch.save(held.where((both > 0) & (both * (1 + similarity) >= total * similarity - 1e-9)).select("a", "b"))
    scratch.drop(ids, sets)
    return links


def _may_resemble(a: str, b: str, similarity: float) -> F.Column:
    """Whether two sets that share the shingle at these positions can have that similarity, by their sizes and by what stands before and after it."""
    size_a, size_b, at_a, at_b = (F.col(f"{side}_{c}") for c in ("n", "pos") for side in (a, b))
    both = F.least(at_a, at_b) + F.least(size_a - at_a, size_b - at_b)
    return (F.least(size_a, size_b) >= F.greatest(size_a, size_b) * similarity - 1e-9) & (both * (1 + similarity) >= (size_a + size_b) * similarity - 1e-9)


def _members(first: DataFrame, similarity: float, scratch: Scratch) -> DataFrame:
    """``(key, rep, n, pos, x_rep, x_n, x_pos, crowded)``: prefix shingles, without the spare ones, of two sets or more, with the least ``rep`` of the key; ``crowded``: three or more.

    A key is a shingle.  Keys that are not among the common shingles are met in one shuffle, by their neighbours in
    order.  The common ones, which may be in very many texts, are counted before the shuffle; there are at most
    as many as `common_shingles` keeps, so that their list can be broadcast.
    """
    needed = (F.col("n") - F.ceil(F.col("n") * similarity - 1e-9) + 1).cast("int")
    keyed = first.select(F.col("id").alias("rep"), "n", "fresh", F.posexplode(F.slice("prefix", F.lit(1), needed)).alias("pos", "key"))
    in_key = Window.partitionBy("key").orderBy("rep")
    nth, after = F.row_number().over(in_key), [F.lead("rep", k).over(in_key).isNotNull() for k in (1, 2)]
    rare = keyed.where("pos < fresh").select("key", "rep", "n", "pos", F.first(F.struct("rep", "n", "pos")).over(in_key).alias("x"), nth.alias("nth"), after[0].alias("next"), after[1].alias("next2"))
    rare = rare.where("nth > 1 or next").withColumn("crowded", F.expr("nth > 2 or next2 or (nth = 2 and next)"))
    often = keyed.where("pos >= fresh").drop("fresh")
    lists = often.groupBy("key").agg(F.min(F.struct("rep", "n", "pos")).alias("x"), F.count(F.lit(1)).alias("size")).where("size > 1")
    often = often.join(F.broadcast(scratch.save(lists)), "key").withColumn("crowded", F.col("size") > 2)
    cols = ["key", "rep", "n", "pos", *[F.col(f"x.{c}").alias(f"x_{c}") for c in ("rep", "n", "pos")], "crowded"]
    return scratch.save(rare.select(cols).union(often.select(cols)))


def _led_pairs(members: DataFrame, similarity: float, scratch: Scratch) -> DataFrame:
    """Pairs ``(a, b)`` of the least text of a key with each other one."""
    sides = members.select("x_rep", "x_n", "x_pos", *[F.col(c).alias(f"y_{c}") for c in ("rep", "n", "pos")])
    pairs = sides.where("x_rep != y_rep").where(_may_resemble("x", "y", similarity))
    return scratch.save(pairs.select(F.least("x_rep", "y_rep").alias("a"), F.greatest("x_rep", "y_rep").alias("b")).distinct())


def _broadcast_few(df: DataFrame, most: int) -> DataFrame:
    return F.broadcast(df) if df.count() <= most else df


def _crossing_pairs(members: DataFrame, similarity: float, scratch: Scratch) -> DataFrame:
    """Pairs ``(a, b)`` of different components ``c`` under crowded keys, each text with one member of the key."""
    lead = F.min(F.struct(F.xxhash64("key", "rep").alias("o"), "rep", "n", "pos", "c")).alias("lead")
    mixed = members.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi"), lead).where("lo < hi")
    mixed = scratch.save(mixed.select("key", *[F.col(f"lead.{c}").alias(f"x_{c}") for c in ("rep", "n", "pos", "c")]))
    sides = members.select("key", *[F.col(c).alias(f"y_{c}") for c in ("rep", "n", "pos", "c")]).join(_broadcast_few(mixed, 200_000), "key").where("x_c != y_c")
    pairs = sides.where(_may_resemble("x", "y", similarity)).select(F.least("x_rep", "y_rep").alias("a"), F.greatest("x_rep", "y_rep").alias("b"))
    return scratch.save(pairs.distinct())


def _mixed(rows: DataFrame, scratch: Scratch) -> DataFrame:
    """The rows whose ``key`` is in several components ``c``; ``kind`` is equal for keys of the same texts (by chance for others too, which only adds pairs)."""
    kind = F.bit_xor(F.xxhash64("rep")).alias("kind")
    keys = rows.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi"), kind).where("lo < hi").select("key", "kind")
    return rows.join(_broadcast_few(scratch.save(keys), 200_000), "key")


def _close_pairs(members: DataFrame, first: DataFrame, similarity: float, scratch: Scratch) -> DataFrame:
    """Every pair ``(a, b)`` of different components ``c`` under crowded keys that can have that similarity; here a key is two shingles.

    The first ``m + 1`` shingles that two such sets share are among the first ``n - least + 1 + m`` of either, and if shingles are dealt to
    ``m`` bins, two of those are in one bin.  So texts meet under two shingles of a bin, where a shared passage of a few shingles
    seldom brings them together; small sets, whose ``m`` is 0, meet under single shingles.  ``m`` is that of a level of sizes: sets of that
    similarity are in one level or in neighbouring ones, and meet in the upper one.  (Two alone under a key have met before.)
    """
    ids = scratch.save(_mixed(members, scratch).select(F.col("rep").alias("id"), "c").distinct())
    step = math.log(1 / similarity) * (1 + 1e-6)
    own = F.floor(F.log("n") / step)
    asked = first.where(F.size("prefix") > 0).join(_broadcast_few(ids, 500_000), "id").select(F.col("id").alias("rep"), "n", "c", own.alias("own"), F.posexplode("prefix").alias("pos", "key"))
    shingle = scratch.save(_mixed(scratch.save(asked), scratch))
    bins = F.floor(F.exp((F.col("level") - 1) * step) * ((1 - 1e-9) / SPARE))  # no more than the spare shingles of the least set of the level below
    placed = shingle.withColumn("level", F.explode(F.array("own", F.col("own") + 1))).withColumn("m", bins)
    met = ["rep", "n", "c", "own", "level", "m"]
    single = placed.where("m = 0").groupBy(*met, "kind").agg(F.min("pos").alias("pos")).select(F.xxhash64("level", "kind").alias("key"), *met, "pos")
    # shingles of one bin that are in the same texts count as one, or as two of them; the least place of each stands for it
    kinds = placed.where("m > 0").groupBy(*met, F.pmod(F.xxhash64("key"), F.col("m")).alias("bin"), "kind").agg(F.min("pos").alias("pos"), F.count(F.lit(1)).alias("n_of"))
    in_bin = kinds.groupBy(*met, "bin").agg(F.sort_array(F.collect_list(F.struct("kind", "pos", "n_of"))).alias("s"))
    two = F.expr("flatten(transform(s, (x, i) -> transform(slice(s, IF(x.n_of > 1, i + 1, i + 2), size(s)), y -> struct(x.kind AS one, y.kind AS two, greatest(x.pos, y.pos) AS pos))))")
    double = in_bin.select(*met, F.explode(two).alias("p")).select(F.xxhash64("level", "p.one", "p.two").alias("key"), *met, "p.pos")
    keyed = scratch.save(single.unionByName(double).groupBy("key", *met).agg(F.min("pos").alias("pos")))
    groups = scratch.save(_mixed(keyed, scratch).groupBy("kind", *met).agg(F.min("pos").alias("pos")))
    scratch.drop(shingle, keyed)
    side = lambda name: [F.col(c).alias(f"{name}_{c}") for c in ("rep", "n", "pos", "c", "own")]
    pairs = groups.select("kind", "level", "m", *side("x")).join(groups.select("kind", "level", *side("y")), ["kind", "level"]).where("x_c < y_c and greatest(x_own, y_own) = level")
    both = F.col("m") + F.least(F.col("x_n") - F.col("x_pos"), F.col("y_n") - F.col("y_pos"))  # at most m are shared before the later one
    near = (F.least("x_n", "y_n") >= F.greatest("x_n", "y_n") * similarity - 1e-9) & (both * (1 + similarity) >= (F.col("x_n") + F.col("y_n")) * similarity - 1e-9)
    return scratch.save(pairs.where(near).select(F.least("x_rep", "y_rep").alias("a"), F.greatest("x_rep", "y_rep").alias("b")).distinct())


def _by_prefixes(pairs: DataFrame, first: DataFrame, similarity: float, scratch: Scratch) -> DataFrame:
    """The pairs that can resemble by their whole prefixes: the set whose prefix ends first in the order has only what follows it left to share.

    Of a shingle's hash 16 bits travel with the pairs.  Unequal shingles may look equal by them, which keeps pairs; shingles of one set
    that look equal are counted on top, so that none in common is missed.
    """
    ids = scratch.save(pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct())
    asked = F.broadcast(ids) if ids.count() <= 500_000 else ids  # so that only the prefixes asked for travel
    short = F.transform("prefix", lambda s: (s.bitwiseAND(F.lit(0xFFFF)) - 32768).cast("short"))
    ends = first.where(F.size("prefix") > 0).join(asked, "id", "left_semi").select("id", "n", F.size("prefix").alias("p"), F.array_distinct(short).alias("short"), F.struct("w", F.element_at("prefix", -1).bitwiseXOR(F.lit(-(1 << 63)))).alias("last"))
    side = lambda name: ends.select(F.col("id").alias(name), *[F.col(c).alias(f"{name}_{c}") for c in ("n", "p", "short", "last")])
    held = pairs.join(side("b"), "b").join(side("a"), "a")
    rest = F.when(F.col("a_last") <= F.col("b_last"), F.col("a_n") - F.col("a_p")).otherwise(F.col("b_n") - F.col("b_p"))
    alike = F.least(F.col("a_p") - F.size("a_short"), F.col("b_p") - F.size("b_short"))
    both = F.size(F.array_intersect("a_short", "b_short")) + alike + rest
    return scratch.save(held.where(both * (1 + similarity) >= (F.col("a_n") + F.col("b_n")) * similarity - 1e-9).select("a", "b").distinct())


def resembling(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similarity: float = 0.8, words: int = 5, seed: int = 42) -> DataFrame:
    """``(id, component)``: groups of documents connected by pairs whose sets of word shingles have that Jaccard similarity or more.

    Texts of equal shingle sets are merged first.  Two different sets of that similarity have a shingle in
    common among the first of each in any fixed order, here rare ones first; these are the join keys.  First
    every text of a key is compared with one text of it, then those of other components with another one,
    and then every two texts that are still in different components and share two shingles of one bin (see `_close_pairs`).
    So a group of close copies costs linear work, and no pair is left out: each is compared or connected already.
    Pairs that cannot resemble by their shared prefixes are left before any whole set is fetched; whole sets decide.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "resembling")
    shape = ["n", "d0", "d1"]
    common = common_shingles(docs, text_col, words, seed)
    sets = scratch.save(shingle_prefixes(docs, id_col, text_col, similarity, words, seed, common))
    same = scratch.save(sets.groupBy(*shape).agg(F.min("id").alias("rep")).where("rep is not null"))
    first = scratch.save(sets.join(same.select(F.col("rep").alias("id")).distinct(), "id", "left_semi"))
    whole, sets = sets, scratch.save(sets.select("id", *shape))
    scratch.drop(whole)
    members = _members(first, similarity, scratch)
    edges, linked = spark.createDataFrame([], "a long, b long"), None
    for step in range(3):
        if step == 0:
            pairs = _led_pairs(members, similarity, scratch)
        else:
            crowd, at = members.where("crowded"), F.col("rep")
            if linked is not None:
                crowd, at = crowd.join(linked, crowd.rep == linked.v, "left"), F.coalesce("component", "rep")
            crowd = scratch.save(crowd.select("key", "rep", "n", "pos", at.alias("c")))
            pairs = _crossing_pairs(crowd, similarity, scratch) if step == 1 else _close_pairs(crowd, first, similarity, scratch)
            scratch.drop(crowd)
        pairs = _by_prefixes(pairs, first, similarity, scratch)
        if not pairs.limit(1).count():
            continue
        edges = scratch.save(edges.union(verified_pairs(pairs, docs, id_col, text_col, similarity, words, seed, scratch)))
        scratch.drop(pairs)
        linked = components(spark, edges, scratch=scratch)
    if linked is None:
        linked = components(spark, edges, scratch=scratch)
    scratch.drop(first, members)
    merged = scratch.save(same.join(linked, same.rep == linked.v, "left").select(*shape, F.coalesce("component", "rep").alias("component")))
    return sets.where("id is not null").join(merged, shape).select("id", "component")


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``docs`` with the document of least id of each group; columns and other rows unchanged.

    SimHash with pigeonring filtering links documents first, as its query does, and of each of its components the
    least id goes on.  What those fingerprints miss is then found among these by `resembling`.
    Of rows of equal id one stays.  Rows of null id are kept.  Blank texts form one group.
    """
    scratch = Scratch(docs.sparkSession, "near-duplicates")
    small = lambda df, n: F.broadcast(df) if n <= 1_000_000 else df
    linked = scratch.save(near_duplicates(docs, id_col, text_col).where("id is not null").select("id", "component_id"))
    copies = scratch.save(linked.where("id != component_id").select(F.col("id").alias("_dup")).distinct())
    without = lambda df: df.join(small(copies, copies.count()), F.col(id_col) == F.col("_dup"), "left_anti")
    groups = scratch.save(resembling(without(docs), id_col, text_col, **options))
    copies = scratch.save(copies.union(groups.where("id != component").select("id")).distinct())
    kept = without(docs)
    repeated = scratch.save(groups.groupBy("id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col("id").alias("_rep")))
    if not repeated.limit(1).count():
        return kept
    once = kept.join(repeated, F.col(id_col) == F.col("_rep"), "left_semi").dropDuplicates([id_col])
    return kept.join(repeated, F.col(id_col) == F.col("_rep"), "left_anti").unionByName(once)
