"""N-gram Jaccard join with count vectors in an R-tree.

Shingles are hashed into groups, and the point of a text counts its shingles in each group. The overlap of two texts is
at most the sum over the groups of the smaller count. A box of the R-tree keeps the largest count of each group and the
range of sizes of what is below it, so the same sum bounds a whole subtree; pairs that pass the bound of the points
themselves have their sets compared.

At scale one tree over all texts would compare everything with everything, so the forest has one tree for each
shingle of a prefix: with an overlap of at least ceil(0.8 n), the first n - ceil(0.8 n) + k shingles of both texts, in
any one order, have k members in common, and pairs must meet in as many trees. The order puts shingles of many texts
last, so trees stay small. No link is lost: the order decides the cost alone.

Pairs are never listed within a group of similar texts. First each text is paired with the smallest text of its trees;
the pairs that the bound admits are verified, and what their links connect is a family. Then trees with several
families alone are built and searched, for pairs of different families: the texts outside a tree's largest family are
the queries, so a family of n texts and a few others costs n. Large trees are dealt out as pairs of blocks. A verified
pair travels as one set of shingles, and the text that it is compared with once for every CHUNK of them; a worker holds
one set and streams the others.

Equal sets are joined by their digest first and stand in the search as one representative.
Null or empty texts and texts without words have the empty set and link with nothing. Extra columns do not matter. An
empty table gives no rows. doc_id must be unique. Shingles are compared by 64 bits of hash, equal sets by 128.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hgengine.llm.common import components, cut, hashed_words, shingles, signed, small

GROUPS = 512
#: A shingle of so many texts goes to the end of the order; at most so many are told apart.
COMMON, MOST_COMMON = 48, 1_000_000
#: Members of a tree beyond which it is dealt out as pairs of blocks.
BLOCK = 2_000
#: Texts that are verified against one copy of another text.
CHUNK = 512
#: Children of a node; a tree of no more points is one node, compared at once.
LEAF = 48


def overlap_needed(n: np.ndarray | int, m: np.ndarray | int, percent: int) -> np.ndarray:
    """Smallest overlap of sets of n and m members with 100 * overlap >= percent * union."""
    return -(-percent * (n + m) // (100 + percent))


#: Of every so many shingles of the smaller text, one more must be shared by the prefixes.
STEP = 20


def prefix_length(n: int, percent: int) -> int:
    return n - -(-percent * n // 100) + 1 + n // STEP


class CountVectorTree:
    """R-tree over points of counts, packed by set size; boxes keep the largest counts and the range of sizes."""

    def __init__(self, sizes: np.ndarray, points: np.ndarray, percent: int) -> None:
        self.order = np.argsort(sizes, kind="stable")
        self.sizes, self.points, self.percent = sizes[self.order].astype(np.int64), points[self.order], percent
        starts = np.arange(0, len(sizes), LEAF)
        self.levels = [(np.maximum.reduceat(self.points, starts, axis=0), np.minimum.reduceat(self.sizes, starts), np.maximum.reduceat(self.sizes, starts))]
        while len(self.levels[-1][0]) > LEAF:
            top, low, high = self.levels[-1]
            starts = np.arange(0, len(top), LEAF)
            self.levels.append((np.maximum.reduceat(top, starts, axis=0), np.minimum.reduceat(low, starts), np.maximum.reduceat(high, starts)))

    def query(self, point: np.ndarray, n: int) -> np.ndarray:
        """Positions, in the order given, of members that the bound cannot rule out."""
        nodes, p = np.arange(len(self.levels[-1][0])), self.percent
        for depth in range(len(self.levels) - 1, -1, -1):
            top, low, high = (x[nodes] for x in self.levels[depth])
            least = overlap_needed(n, np.maximum(low, -(-p * n // 100)), p)
            fits = (100 * high >= p * n) & (p * low <= 100 * n) & (n - lacking(point, top) >= least)
            width = len(self.levels[depth - 1][0]) if depth else len(self.sizes)
            nodes = (nodes[fits][:, None] * LEAF + np.arange(LEAF)).ravel()
            nodes = nodes[nodes < width]
        return self.order[nodes[admitted(point, n, self.points[nodes], self.sizes[nodes], p)]]


def lacking(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """What b lacks of the counts of a: the size of a less this is the sum of the smaller counts. Counts stop at 255, which
    can make it less but never more, so the bound stays safe."""
    return (np.maximum(a, b) - b).sum(axis=-1, dtype=np.int64)


def admitted(point: np.ndarray, n: np.ndarray | int, points: np.ndarray, sizes: np.ndarray, percent: int) -> np.ndarray:
    """Whether the sum of coordinate minima admits each pair."""
    fits = (100 * sizes >= percent * n) & (percent * sizes <= 100 * n)
    bound = np.minimum(n - lacking(point, points), sizes - lacking(points, point))
    return fits & (bound >= overlap_needed(n, sizes, percent))


def _common(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def counted() -> pa.RecordBatch:
            values, counts = np.unique(np.concatenate(held), return_counts=True)
            often = counts >= 3
            return pa.RecordBatch.from_arrays([pa.array(signed(values[often])), pa.array(counts[often])], ["shingle", "n"])

        for batch in batches:
            for text in batch.column(0):
                if len(s := np.unique(shingles(hashed_words(text.as_py()), k))):
                    held.append(s)
                    size += len(s)
                if size >= 1_000_000:
                    yield counted()
                    held, size = [], 0
        if held:
            yield counted()

    return run


def common_shingles(docs: DataFrame, k: int) -> np.ndarray:
    """Shingles that many texts have, as a sorted array of at most MOST_COMMON: a hint for the order, not a filter."""
    found = docs.select("text").mapInArrow(_common(k), "shingle long, n long").groupBy("shingle").agg(F.sum("n").alias("n")).where(F.col("n") >= COMMON)
    rows = found.orderBy(F.desc("n"), "shingle").limit(MOST_COMMON).select("shingle").toArrow()
    return np.sort(rows.column(0).to_numpy().astype(np.int64).view(np.uint64))


def point_of(members: np.ndarray) -> bytes:
    counts = np.bincount((members & np.uint64(GROUPS - 1)).astype(np.int64), minlength=GROUPS)
    return np.minimum(counts, 255).astype(np.uint8).tobytes()


def points_of(column: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(column), np.uint8).reshape(-1, GROUPS)


def _sets(k: int, percent: int, common):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        often = common.value
        for batch in batches:
            ids, sizes, keys, vectors, prefixes = [], [], [], [], []
            for doc, text in zip(batch.column(0), batch.column(1), strict=True):
                s = np.unique(shingles(hashed_words(text.as_py()), k))
                ids.append(doc.as_py())
                sizes.append(len(s))
                keys.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                vectors.append(point_of(s))
                length = prefix_length(len(s), percent) if len(s) else 0
                if len(often) and length:
                    at = np.searchsorted(often, s).clip(max=len(often) - 1)
                    last = often[at] == s
                    s = np.concatenate([s[~last][:length], s[last][: max(0, length - int((~last).sum()))]])
                prefixes.append(signed(s[:length]))
            offsets = np.cumsum([0, *map(len, prefixes)]).astype(np.int32)
            flat = np.concatenate([*prefixes, np.zeros(0, np.int64)])
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids, pa.int64()), pa.array(sizes, pa.int64()), pa.array(keys, pa.binary()), pa.array(vectors, pa.binary()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))],
                ["doc_id", "n_shingles", "set_key", "point", "prefix"],
            )

    return run


def _shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows (shingle, doc_id, n) sorted by shingle and doc_id, those whose shingle another row has, with the first
    text of the shingle and its size."""
    held = None  # the last row, whether it was given, and the first of its shingle
    for batch in batches:
        if not batch.num_rows:
            continue
        s, d, n = (batch.column(i).to_numpy() for i in range(3))
        if held:
            s, d, n = (np.append(h, x) for h, x in zip(held[:3], (s, d, n), strict=True))
        same = s[1:] == s[:-1]
        heads = np.nonzero(np.append(True, ~same))[0]
        of = np.repeat(heads, np.diff(np.append(heads, len(s))))
        first, first_n = d[of], n[of]
        if held:
            own = of == 0
            first[own], first_n[own] = held[4], held[5]
        keep = np.append(False, same) | np.append(same, False)
        given = bool(keep[-1]) or bool(held and held[3] and len(s) == 1)
        if held and held[3]:
            keep[0] = False
        held = (s[-1], d[-1], n[-1], given, first[-1], first_n[-1])
        yield pa.RecordBatch.from_arrays([pa.array(x[keep]) for x in (s, d, n, first, first_n)], ["shingle", "doc_id", "n", "first", "first_n"])


def _meetings(percent: int):
    """Pairs of texts that meet in trees: of rows sorted by tree and its blocks, how often probes meet builds of another
    family that the bound admits."""
    keys = ("shingle", "i", "j")

    def pairs(ids, sizes, points, family, minor, build, probe) -> tuple[np.ndarray, np.ndarray]:
        """Indices of a tree's pairs."""
        none = np.zeros(0, np.int64), np.zeros(0, np.int64)
        if not probe.any() or (family == family[0]).all():
            return none
        if len(ids) <= LEAF:
            a, b = np.nonzero(probe[:, None] & build & (family[:, None] != family) & (~minor | (ids[:, None] < ids)))
            fits = admitted(points[a], sizes[a], points[b], sizes[b], percent)
            return a[fits], b[fits]
        own, queries = np.nonzero(build)[0], np.nonzero(probe)[0]
        if not len(own):
            return none
        tree = CountVectorTree(sizes[own], points[own], percent)
        met = [own[tree.query(points[q], int(sizes[q]))] for q in queries]
        a, b = np.repeat(queries, list(map(len, met))), np.concatenate(met)
        apart = (family[a] != family[b]) & (~minor[b] | (ids[a] < ids[b]))
        return a[apart], b[apart]

    def found(rows: pa.Table) -> pa.RecordBatch:
        ids, sizes, times, family, minor, build, probe = (rows.column(n).to_numpy(zero_copy_only=False) for n in ("doc_id", "n", "times", "family", "minor", "build", "probe"))
        points = points_of(rows.column("point").to_pylist())
        tree = np.stack([rows.column(n).to_numpy() for n in keys])
        heads = np.append(0, np.nonzero(np.any(tree[:, 1:] != tree[:, :-1], axis=0))[0] + 1)
        size = np.diff(np.append(heads, len(ids)))
        # trees of two texts all at once
        a, b = heads[size == 2], heads[size == 2] + 1
        fits = (family[a] != family[b]) & ((probe[a] & build[b]) | (probe[b] & build[a]))
        a, b = a[fits], b[fits]
        fits = admitted(points[a], sizes[a], points[b], sizes[b], percent)
        met = [(a[fits], b[fits])]
        for lo, n in zip(heads[size > 2].tolist(), size[size > 2].tolist(), strict=True):
            hi = lo + n
            x, y = pairs(*(c[lo:hi] for c in (ids, sizes, points, family, minor, build, probe)))
            met.append((lo + x, lo + y))
        a, b = (np.concatenate([m[i] for m in met]) for i in (0, 1))
        a, b = np.where(ids[a] < ids[b], a, b), np.where(ids[a] < ids[b], b, a)
        both, at, of = np.unique(np.stack([ids[a], ids[b]]), axis=1, return_index=True, return_inverse=True)
        n = np.bincount(of.ravel(), times[a], len(at)).astype(np.int64)
        return pa.RecordBatch.from_arrays([pa.array(x) for x in (both[0], both[1], sizes[a[at]], sizes[b[at]], n)], ["a", "b", "n_a", "n_b", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Table] = []  # the last tree, which may go on in the next batch
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(pa.Table.from_batches([batch]))
            first, last = ([held[i].column(n)[i].as_py() for n in keys] for i in (0, -1))
            if first == last:
                continue
            whole = pa.concat_tables(held)
            tree = np.stack([whole.column(n).to_numpy() for n in keys])
            at = int(np.nonzero(np.any(tree != np.array(last)[:, None], axis=0))[0][-1]) + 1
            yield found(whole.slice(0, at))
            held = [whole.slice(at)]
        if held:
            yield found(pa.concat_tables(held))

    return run


def _bounded(percent: int):
    """Of pairs with both points, those that the bound admits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                p, q = (points_of(batch.column(n).to_pylist()) for n in ("point_a", "point_b"))
                n, m = (batch.column(x).to_numpy() for x in ("n_a", "n_b"))
                yield batch.select(["a", "b"]).filter(pa.array(admitted(p, n, q, m, percent)))

    return run


def _members(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        doc, members = None, b""
        for batch in batches:
            sets = []
            for d, t in zip(batch.column("doc_id").to_pylist(), batch.column("text"), strict=True):
                if d != doc:  # the rows of a text stand together
                    doc, members = d, np.unique(shingles(hashed_words(t.as_py()), k)).tobytes()
                sets.append(members)
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in ("a", "chunk", "center", "doc_id")), pa.array(sets, pa.binary())], ["a", "chunk", "center", "doc_id", "members"])

    return run


def _verified(percent: int):
    """Of sets sorted by a and chunk, the set of a first: links with overlap."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        center = np.zeros(0, np.uint64)
        for batch in batches:
            out: list[list] = [[], [], []]
            for a, is_center, b, members in zip(*(batch.column(n) for n in ("a", "center", "doc_id", "members")), strict=True):
                s = np.frombuffer(members.as_buffer(), np.uint64)
                if is_center.as_py():
                    center = s.copy()
                    continue
                at = np.searchsorted(center, s)
                at[at == len(center)] = 0
                overlap = int((center[at] == s).sum())
                if 100 * overlap >= percent * (len(center) + len(s) - overlap):
                    for column, value in zip(out, (a.as_py(), b.as_py(), overlap), strict=True):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], ["a", "b", "overlap"])

    return run


def verified(docs: DataFrame, pairs: DataFrame, k: int, percent: int) -> DataFrame:
    """a, b, overlap of the pairs (a, b; cut) that link. The sets of all b travel once, that of a once for each CHUNK."""
    heavy = cut(pairs.groupBy("a").agg(F.ceil(F.count("*") / F.lit(CHUNK)).cast("int").alias("chunks")).where("chunks > 1"))
    dealt = pairs.join(small(heavy), "a", "left").select("a", "b", F.coalesce(F.pmod(F.xxhash64("b"), F.col("chunks")), F.lit(0)).cast("int").alias("chunk"))
    wanted = dealt.select("a", "chunk", F.lit(False).alias("center"), F.col("b").alias("doc_id")).unionByName(dealt.select("a", "chunk", F.lit(True).alias("center"), F.col("a").alias("doc_id")).distinct())
    sets = docs.join(small(cut(wanted)), "doc_id").select("doc_id", "text", "a", "chunk", "center").mapInArrow(_members(k), "a long, chunk int, center boolean, doc_id long, members binary")
    return sets.repartition("a", "chunk").sortWithinPartitions("a", "chunk", F.desc("center")).mapInArrow(_verified(percent), "a long, b long, overlap long")


def _near(n: str, a: str, b: str, percent: int) -> Column:
    """Whether texts of a and b shingles may link after n meetings."""
    return F.expr(f"{n} >= 1 + least({a}, {b}) div {STEP} and 100 * least({a}, {b}) >= {percent} * greatest({a}, {b})")


def jaccard_links(docs: DataFrame, k: int = 5, percent: int = 80, every: bool = True) -> tuple[DataFrame, DataFrame]:
    """(classes, links): classes has doc_id, n_shingles and rep, the smallest doc_id of the same set (null for empty
    sets); links has pairs a < b of representatives with 100 * overlap >= percent * union, and overlap: all, or with
    every=False as many as connect the same texts.

    Only doc_id and text are read; other columns do not matter. doc_id must be unique."""
    spark, docs = docs.sparkSession, docs.select("doc_id", "text")
    common = spark.sparkContext.broadcast(common_shingles(docs, k))
    sets = cut(docs.mapInArrow(_sets(k, percent, common), "doc_id long, n_shingles long, set_key binary, point binary, prefix array<long>"))
    full = sets.where("set_key is not null")
    copied = cut(full.groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")).where("n > 1").drop("n"))
    full = full.join(small(copied), "set_key", "left").withColumn("rep", F.coalesce("rep", "doc_id"))
    classes = full.select("doc_id", "n_shingles", "rep").unionByName(sets.where("set_key is null").select("doc_id", "n_shingles", F.lit(None).cast("long").alias("rep")))
    classes = cut(classes)
    alone = full.where("doc_id = rep").select("doc_id", F.col("n_shingles").alias("n"), "point", "prefix")
    # one sort finds the shingles that two texts share
    dealt = alone.select(F.explode("prefix").alias("shingle"), "doc_id", "n").repartition("shingle").sortWithinPartitions("shingle", "doc_id")
    shared = cut(dealt.mapInArrow(_shared, "shingle long, doc_id long, n long, first long, first_n long"))
    members = shared.select("shingle", "doc_id", "n")
    points = alone.select("doc_id", "point")
    if every:
        links = None
        members = members.withColumn("family", F.col("doc_id"))
    else:
        stars = shared.where("doc_id <> first").groupBy(F.col("first").alias("a"), F.col("doc_id").alias("b")).agg(F.count("*").alias("n"), F.first("first_n").alias("n_a"), F.first("n").alias("n_b")).where(_near("n", "n_a", "n_b", percent))
        for x in "ab":
            stars = stars.join(points.select(F.col("doc_id").alias(x), F.col("point").alias(f"point_{x}")), x)
        links = cut(verified(docs, cut(stars.select("a", "b", "n_a", "n_b", "point_a", "point_b").mapInArrow(_bounded(percent), "a long, b long")), k, percent))
        roots = components(links).select(F.col("node").alias("doc_id"), F.col("root").alias("family"))
        members = members.join(roots, "doc_id", "left").withColumn("family", F.coalesce("family", "doc_id"))
    # trees of several families; trees of the same texts are one, which counts as often (texts by 128 bits of hash). One
    # exchange serves both sides
    members = members.repartition("shingle")
    marks = [F.bit_xor(F.xxhash64("doc_id", F.lit(m))).alias(f"mark_{m}") for m in "xy"]
    counts = members.groupBy("shingle", "family").agg(F.count("*").alias("n_family"), *marks)
    trees = counts.groupBy("shingle").agg(F.max_by("family", F.struct("n_family", "family")).alias("major"), F.sum("n_family").alias("n_all"), F.max("n_family").alias("n_major"), F.count("*").alias("families"), *(F.bit_xor(f"mark_{m}").alias(f"mark_{m}") for m in "xy"))
    trees = trees.where("families > 1").groupBy("mark_x", "mark_y", "n_all").agg(F.min("shingle").alias("shingle"), F.count("*").alias("times"), F.first("major").alias("major"), F.first("n_major").alias("n_major")).drop("mark_x", "mark_y")
    rows = cut(members.join(trees, "shingle"))
    # the texts that meet often enough to have a link
    enough = cut(rows.groupBy("doc_id").agg(F.sum("times").alias("meets"), F.first("n").alias("n")).where(F.expr(f"meets >= 1 + (({percent} * n + 99) div 100) div {STEP}")).select("doc_id"))
    blocks = lambda n: F.greatest(F.lit(1), F.ceil(n / F.lit(BLOCK))).cast("int")
    rows = rows.join(small(enough), "doc_id", "left_semi").withColumns({"minor": F.col("family") != F.col("major"), "of_i": blocks(F.col("n_all")), "of_j": blocks(F.col("n_all") - F.col("n_major"))})
    rows = rows.withColumns({"own_i": F.pmod(F.xxhash64("doc_id"), "of_i").cast("int"), "own_j": F.pmod(F.xxhash64("doc_id", F.lit("probe")), "of_j").cast("int")})
    builds = F.transform(F.sequence(F.lit(0), F.col("of_j") - 1), lambda j: F.struct(F.col("own_i").alias("i"), j.alias("j"), F.lit(True).alias("build"), (F.col("minor") & (j == F.col("own_j"))).alias("probe")))
    probes = F.transform(F.filter(F.sequence(F.lit(0), F.col("of_i") - 1), lambda i: F.col("minor") & (i != F.col("own_i"))), lambda i: F.struct(i.alias("i"), F.col("own_j").alias("j"), F.lit(False).alias("build"), F.lit(True).alias("probe")))
    rows = rows.join(points, "doc_id").select("shingle", "times", "doc_id", "n", "family", "minor", "point", F.inline(F.concat(builds, probes)))
    met = rows.repartition("shingle", "i", "j").sortWithinPartitions("shingle", "i", "j").mapInArrow(_meetings(percent), "a long, b long, n_a long, n_b long, n long")
    strange = met.groupBy("a", "b").agg(F.sum("n").alias("n"), F.first("n_a").alias("n_a"), F.first("n_b").alias("n_b")).where(_near("n", "n_a", "n_b", percent)).select("a", "b")
    more = verified(docs, cut(strange), k, percent)
    return classes, cut(more if links is None else links.unionByName(more))


def near_duplicate_components(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id: the smallest doc_id that links reach."""
    classes, links = jaccard_links(docs, k, percent, every=False)
    roots = cut(components(links).select(F.col("node").alias("rep"), "root"))
    empty = classes.where("rep is null").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    full = classes.where("rep is not null").join(small(roots), "rep", "left").select("doc_id", "n_shingles", F.coalesce("root", "rep").alias("component_id"))
    return full.unionByName(empty)


def one_of_each(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """docs without those that have a near duplicate of smaller doc_id in their component."""
    gone = cut(near_duplicate_components(docs, k, percent).where("doc_id <> component_id").select("doc_id"))
    return docs.join(small(gone), "doc_id", "left_anti").select(docs.columns)
