"""N-gram Jaccard join: MinHash bands propose pairs, full n-gram sets decide.

1. One map pass makes, per document, a 128-bit identity of its set of word n-grams and its band
   hashes. Documents with equal sets form a *copy class* (combined map-side), so a text that a third of
   the rows repeat is one row from here on.
2. Band hashes of class representatives are grouped; each bucket proposes its members against
   its least member (a star, linear in the bucket), then against further pivots of components not yet joined.
3. Pairs are verified with exact Jaccard on the whole n-gram sets, which are made once for the
   documents that share any bucket.
4. Connected components of the verified links give the near-duplicate class.
5. To lose no link between components, buckets that still hold several afterwards are finished exactly: small ones
   by all pairs across components, large ones by the pairs whose rarest n-grams overlap (a prefix filter, which loses no
   pair at the threshold). The classes need no pair inside a component, so there groups of near copies cost a few pairs per member.
6. All links lie inside components, so the links and their number per document come from every pair of a component: its members
   are dealt into blocks of bounded size, and each pair of blocks is one unit of work, which counts common n-grams for all
   pairs at once. Output rows are degrees; the links themselves are made only when they are read.

`bands_for` picks rows and bands so that a pair at the threshold is proposed with the target recall.

Defined cases: null text is empty; texts without words are copies only when equal byte for byte; 1 to
n-1 words make one n-gram of all of them; rows that repeat an id are read as one document (first text by hash); a null id
gets a null class and no links; empty tables give empty results; other columns are not read (`keep_one` carries them, whatever
their names).
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._tables import Workspace, unused
from ._text import buffers, distinct_per_row, grams, mix, segment_min, steps, token_hashes, tokens

#: Mixed buckets of at most this many members are finished pair by pair, larger ones by prefixes.
SMALL = 16
#: Bounds of one block of a component (members, n-grams), and of the tiles in which two blocks are compared.
BLOCK_MEMBERS, BLOCK_GRAMS = 8192, 1 << 22
TILE, COLUMNS, EXPANDED = 1024, 4096, 1 << 22
#: An n-gram that makes at most this many pairs in a tile is expanded, a more common one is a column of a matrix product.
LIGHT = 4096


def bands_for(similarity: float, recall: float, most_hashes: int = 128) -> tuple[int, int]:
    """(bands, rows): as many rows as the budget of hashes allows at the target recall."""
    best = (most_hashes, 1)
    for rows in range(1, most_hashes + 1):
        hit = similarity**rows
        bands = 1 if hit >= recall else math.ceil(math.log(1 - recall) / math.log(1 - hit))
        if bands * rows <= most_hashes:
            best = (bands, rows)
    return best


def _factors(count: int) -> tuple[np.ndarray, np.ndarray]:
    x = mix(np.arange(1, 2 * count + 1, dtype=np.uint64))
    return x[:count] | np.uint64(1), x[count:]


def _gram_sets(column: pa.Array, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    raw, offsets = buffers(column)
    s, e, first = tokens(raw, offsets)
    values, begin = grams(token_hashes(raw, s, e), first, n)
    return *distinct_per_row(values, begin), raw, offsets


def signatures(docs: DataFrame, n: int, bands: int, rows: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, a, b, n, bands): identity of the n-gram set, its size and its band hashes."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        factor, shift = _factors(bands * rows)
        join = mix(np.arange(101, 101 + rows, dtype=np.uint64)) | np.uint64(1)
        for part in steps(batches, "text"):
            values, begin, raw, offsets = _gram_sets(part.column("text"), n)
            size = np.diff(begin)
            total = [np.concatenate([[np.uint64(0)], np.cumsum(mix(values ^ np.uint64(c)))]) for c in (0x51, 0xA7)]
            a, b = (t[begin[1:]] - t[begin[:-1]] for t in total)
            bare = np.flatnonzero(size == 0)
            if len(bare):
                a[bare] = token_hashes(raw, offsets[:-1][bare], offsets[1:][bare], fold=False) if len(raw) else 0
            out = np.zeros((len(size), bands), np.uint64)
            for k in range(bands):
                for r in range(rows):
                    j = k * rows + r
                    out[:, k] += mix(segment_min(values * factor[j] + shift[j], begin, np.uint64(0))) * join[r]
            out = mix(out.reshape(-1)).view(np.int64).reshape(-1, bands)[size > 0]
            at = np.concatenate([[0], np.cumsum(np.where(size > 0, bands, 0))]).astype(np.int32)
            yield pa.RecordBatch.from_arrays(
                [part.column("doc_id"), pa.array(a.view(np.int64)), pa.array(b.view(np.int64)), pa.array(size.astype(np.int32)), pa.ListArray.from_arrays(pa.array(at), pa.array(out.reshape(-1)))],
                ["doc_id", "a", "b", "n", "bands"],
            )

    rows_in = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return rows_in.mapInArrow(sign, "doc_id long, a long, b long, n int, bands array<long>")


def gram_table(docs: DataFrame, n: int) -> DataFrame:
    """(doc_id, grams): sorted distinct n-gram hashes."""

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in steps(batches, "text"):
            values, begin, _, _ = _gram_sets(part.column("text"), n)
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.ListArray.from_arrays(pa.array(begin.astype(np.int32)), pa.array(values.view(np.int64)))], ["doc_id", "grams"])

    return docs.mapInArrow(make, "doc_id long, grams array<long>")


def verify(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Pairs (x, y) with their exact Jaccard."""
    left = sets.select(F.col("doc_id").alias("x"), F.col("grams").alias("gx"))
    right = sets.select(F.col("doc_id").alias("y"), F.col("grams").alias("gy"))
    both = pairs.join(left, "x").join(right, "y").withColumn("i", F.size(F.array_intersect("gx", "gy")))
    return both.select("x", "y", (F.col("i") / (F.size("gx") + F.size("gy") - F.col("i"))).alias("jaccard"))


def components(space: Workspace, edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, root) for all nodes with an edge (src, dst); root is the least node of the component.

    Alternates two contractions until nothing changes: every node hands its larger neighbours to its least
    neighbour, then every node hands its smaller neighbours to the least of them. Node degrees never meet in one
    task: minima are combined map-side and the join back is a plain equi-join.
    """
    pair = lambda df: df.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    links = space.write(pair(edges.select(F.col("src").alias("u"), F.col("dst").alias("v"))))
    seen = None
    for _ in range(rounds):
        sign = tuple(links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first())
        if sign == seen:
            break
        seen = sign
        sym = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = sym.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = space.write(pair(sym.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))))
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        moved = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        new = space.write(pair(moved.unionByName(least.select("u", F.col("m").alias("v")))))
        space.drop(links, large)
        links = new
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    roots = links.select(F.col("u").alias("node"), F.col("v").alias("root"))
    return roots.unionByName(links.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())


def _all(tables: list[DataFrame]) -> DataFrame:
    out = tables[0]
    for more in tables[1:]:
        out = out.unionByName(more)
    return out


def _small_buckets(rest: DataFrame) -> DataFrame:
    """All pairs across components in buckets of at most `SMALL` members."""
    theirs = rest.select("band", "h", F.col("rep").alias("rep2"), F.col("n").alias("n2"), F.col("root").alias("root2"))
    return rest.join(theirs, ["band", "h"]).filter("root < root2").select("rep", "n", "rep2", "n2")


def _by_prefix(members: DataFrame, sets: DataFrame, similarity: float, space: Workspace) -> DataFrame:
    """Pairs across components of large buckets that can reach the similarity at all.

    Two sets of Jaccard s share one of the first n - ceil(s n) + 1 n-grams of each when all sets are read in one
    order. N-grams of a single component come first: they link nothing, so they are only counted, and a document whose
    own component's n-grams fill that prefix meets nobody. The others follow, rare ones first.
    """
    grams = space.write(members.join(sets, members["rep"] == sets["doc_id"]).select("rep", "n", "root", F.size("grams").alias("m"), F.explode("grams").alias("g")))
    bridging = grams.groupBy("g").agg(F.count(F.lit(1)).alias("f"), F.min("root").alias("lo"), F.max("root").alias("hi")).filter("lo < hi").select("g", "f")
    ranked = grams.join(bridging, "g").groupBy("rep", "n", "root", "m").agg(F.array_sort(F.collect_list(F.struct("f", "g"))).alias("s"))
    own = F.col("m") - F.size("s")
    size = F.greatest(F.col("m") - F.ceil(F.col("m") * F.lit(similarity) - 1e-9).cast("int") + 1 - own, F.lit(0))
    first = space.write(ranked.select("rep", "n", "root", "m", own.alias("own"), F.posexplode(F.slice("s", F.lit(1), size)).alias("i", "t")).select("rep", "n", "root", "m", (F.col("own") + F.col("i")).alias("at"), F.col("t.g").alias("g")))
    # Only n-grams that several components hold in their prefixes can link them.
    meeting = first.groupBy("g").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).filter("lo < hi").select("g")
    mine = space.write(first.join(meeting, "g"))
    theirs = mine.select("g", F.col("rep").alias("rep2"), F.col("n").alias("n2"), F.col("root").alias("root2"), F.col("m").alias("m2"), F.col("at").alias("at2"))
    # The least common n-gram stands at the first places both have in common, so what follows it bounds the overlap.
    reach = F.least(F.col("m") - F.col("at"), F.col("m2") - F.col("at2")) >= similarity / (1 + similarity) * (F.col("m") + F.col("m2")) - 1e-9
    return mine.join(theirs, "g").filter((F.col("root") < F.col("root2")) & reach).select("rep", "n", "rep2", "n2").distinct()


def _common(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Number of n-grams that each set of *left* shares with each of *right*."""
    out = np.zeros(len(left) * len(right), np.int64)
    shared = np.intersect1d(np.concatenate(left), np.concatenate(right))
    if not len(shared):
        return out.reshape(len(left), len(right))

    def entries(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        values, row = np.concatenate(sets), np.repeat(np.arange(len(sets)), [len(x) for x in sets])
        code = np.minimum(np.searchsorted(shared, values), len(shared) - 1)
        held = shared[code] == values
        code, row = code[held], row[held]
        order = np.argsort(code, kind="stable")
        return code[order], row[order], np.bincount(code, minlength=len(shared))

    (ca, ra, fa), (cb, rb, fb) = entries(left), entries(right)
    heavy = fa * fb > LIGHT
    first = np.cumsum(fa) - fa
    cl, rl = cb[~heavy[cb]], rb[~heavy[cb]]
    total = np.cumsum(fa[cl])
    at = 0
    while at < len(cl):
        to = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + EXPANDED, side="right")))
        times = fa[cl[at:to]]
        within = np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
        rows = ra[np.repeat(first[cl[at:to]], times) + within]
        out += np.bincount(rows * len(right) + np.repeat(rl[at:to], times), minlength=len(out))
        at = to
    out = out.reshape(len(left), len(right))
    number = np.cumsum(heavy) - 1
    (ca, ra), (cb, rb) = ((number[c[heavy[c]]], r[heavy[c]]) for c, r in ((ca, ra), (cb, rb)))
    for low in range(0, int(heavy.sum()), COLUMNS):
        sides = []
        for c, r, count in ((ca, ra, len(left)), (cb, rb, len(right))):
            i, j = np.searchsorted(c, [low, low + COLUMNS])
            dense = np.zeros((count, COLUMNS), np.float32)  # counts up to COLUMNS are exact
            dense[r[i:j], c[i:j] - low] = 1
            sides.append(dense)
        out += (sides[0] @ sides[1].T).astype(np.int64)
    return out


def _unit_links(side: np.ndarray, sets: list[np.ndarray], similarity: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(rows, rows, jaccard) of the links of one unit: all pairs of one block, or all pairs between two."""
    size = np.array([len(x) for x in sets])
    parts = [[b[k : k + TILE] for k in range(0, len(b), TILE)] for b in (np.flatnonzero(side == p)[np.argsort(size[side == p], kind="stable")] for p in np.unique(side))]
    alone = len(parts) == 1
    for m, a in enumerate(parts[0]):
        for b in parts[0][m:] if alone else parts[1]:
            low, high = max(size[a[0]], size[b[0]]), min(size[a[-1]], size[b[-1]])
            if high < similarity * low:  # too unlike in size for any link
                continue
            both = _common([sets[i] for i in a], [sets[i] for i in b])
            jaccard = both / (size[a][:, None] + size[b][None, :] - both)
            hit = jaccard >= similarity
            if alone and a is b:
                hit = np.triu(hit, 1)
            x, y = np.nonzero(hit)
            yield a[x], b[y], jaccard[x, y]


def _units(space: Workspace, roots: DataFrame, sets: DataFrame) -> DataFrame:
    """(root, i, j, p, node, grams) in order of units: the members of blocks i and j of a component; p is the own block."""
    held = roots.join(sets, roots["node"] == sets["doc_id"]).select("root", "node", "grams")
    k = F.ceil(F.greatest(F.count(F.lit(1)) / BLOCK_MEMBERS, F.sum(F.size("grams")) / BLOCK_GRAMS)).cast("int")
    blocks = space.write(held.groupBy("root").agg(k.alias("k")))
    placed = held.join(blocks, "root").withColumn("p", F.pmod(F.xxhash64("node"), F.col("k")).cast("int"))
    placed = placed.withColumn("q", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    units = placed.select("root", F.least("p", "q").alias("i"), F.greatest("p", "q").alias("j"), "p", "node", "grams")
    return units.repartition("root", "i", "j").sortWithinPartitions("root", "i", "j")


def _per_unit(units: DataFrame, similarity: float, pairs: bool) -> DataFrame:
    """(x, y, jaccard) of all links, or (node, n_links) with one row for each unit that links a node."""

    def result(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        ids, side = np.array([r[0] for r in rows]), np.array([r[1] for r in rows])
        degree = np.zeros(len(ids), np.int64)
        for x, y, jaccard in _unit_links(side, [r[2] for r in rows], similarity):
            if pairs:
                u, v = ids[x], ids[y]
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(u, v)), pa.array(np.maximum(u, v)), pa.array(jaccard)], ["x", "y", "jaccard"])
            else:
                degree += np.bincount(x, minlength=len(ids)) + np.bincount(y, minlength=len(ids))
        if not pairs:
            some = np.flatnonzero(degree)
            yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(degree[some])], ["node", "n_links"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, rows = None, []
        for batch in batches:
            root, i, j, p, node = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("root", "i", "j", "p", "node"))
            for k, grams in enumerate(batch.column("grams")):
                if (new := (root[k], i[k], j[k])) != key:
                    if rows:
                        yield from result(rows)
                    key, rows = new, []
                rows.append((node[k], p[k], grams.values.to_numpy().copy()))
        if rows:
            yield from result(rows)

    return units.mapInArrow(run, "x long, y long, jaccard double" if pairs else "node long, n_links long")


def _near(docs: DataFrame, n: int = 5, similarity: float = 0.8, recall: float = 0.999, id_col: str = "doc_id", text_col: str = "text") -> tuple[Workspace, DataFrame, DataFrame, DataFrame, DataFrame]:
    """Workspace, signatures, copy classes, n-gram sets of the documents that share a bucket, components (node, root)."""
    space = Workspace(docs.sparkSession, "jaccard")
    bands, rows = bands_for(similarity, recall)
    signed = space.write(signatures(docs, n, bands, rows, id_col, text_col))
    classes = signed.groupBy("a", "b", "n").agg(F.min("doc_id").alias("rep"), F.first("bands").alias("bands"))
    classes = space.write(classes)

    held = classes.filter("rep is not null").select("rep", "n", F.posexplode("bands").alias("band", "h"))
    # Ties of ids are broken by size, so that a bucket has one least member whatever the order.
    shared = held.groupBy("band", "h").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").select("band", "h")
    held = space.write(held.join(shared, ["band", "h"]))
    close = (F.least("n", "n2") >= similarity * F.greatest("n", "n2")) & (F.col("rep") != F.col("rep2"))
    pair = [F.least("rep", "rep2").alias("x"), F.greatest("rep", "rep2").alias("y")]

    ids = held.select(F.col("rep").alias("_id")).distinct()
    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    picked = picked.join(ids.hint("shuffle_hash"), F.col("doc_id") == F.col("_id"), "left_semi")
    sets = gram_table(picked, n).groupBy("doc_id").agg(F.min("grams").alias("grams"))
    sets = space.write(sets)

    least = held.groupBy("band", "h").agg(F.min(F.struct("rep", "n")).alias("p"))
    star = held.join(least.select("band", "h", F.col("p.rep").alias("rep2"), F.col("p.n").alias("n2")), ["band", "h"])
    tested = [space.write(verify(star.filter(close).select(*pair).distinct(), sets))]
    for turn in range(2):
        known = _all(tested)
        roots = components(space, known.filter(F.col("jaccard") >= similarity).select(F.col("x").alias("src"), F.col("y").alias("dst")))
        labelled = space.write(held.join(roots, held["rep"] == roots["node"], "left").select("band", "h", "rep", "n", F.coalesce("root", "rep").alias("root")))
        mixed = labelled.groupBy("band", "h").agg(
            F.min("root").alias("lo"), F.max("root").alias("hi"), F.count(F.lit(1)).alias("c"),
            F.min(F.struct("root", F.xxhash64("rep"), "rep", "n")).alias("p"), F.max(F.struct("root", F.xxhash64("rep"), "rep", "n")).alias("q"),
        ).filter("lo < hi")
        if turn == 0:  # a member of another component as pivot
            other = F.when(F.col("root") == F.col("lo"), F.col("q")).otherwise(F.col("p"))
            wide = labelled.join(mixed.select("band", "h", "p", "q", "lo"), ["band", "h"]).withColumn("o", other)
            pairs = wide.select("rep", "n", F.col("o.rep").alias("rep2"), F.col("o.n").alias("n2"))
        else:  # whatever may still link components
            pairs = _small_buckets(labelled.join(mixed.filter(F.col("c") <= SMALL).select("band", "h"), ["band", "h"]))
            large = labelled.join(mixed.filter(F.col("c") > SMALL).select("band", "h"), ["band", "h"]).select("rep", "n", "root").distinct()
            pairs = pairs.unionByName(_by_prefix(space.write(large), sets, similarity, space))
        pairs = pairs.filter(close).select(*pair).distinct().join(known.select("x", "y"), ["x", "y"], "left_anti")
        tested.append(space.write(verify(pairs, sets)))
        space.drop(labelled)
    links = _all(tested).filter(F.col("jaccard") >= similarity)
    if not tested[-1].filter(F.col("jaccard") >= similarity).isEmpty():  # otherwise the last components stand
        roots = components(space, links.select(F.col("x").alias("src"), F.col("y").alias("dst")))
    return space, signed, classes, sets, roots


def _label(space: Workspace, signed: DataFrame, classes: DataFrame, nodes: DataFrame) -> DataFrame:
    """doc_id, copy_id, class_id, n_links from (node, root, n_links) of the linked representatives."""
    of_class = classes.select("a", "b", "n", "rep").join(nodes, F.col("rep") == F.col("node"), "left")
    of_class = space.write(of_class.select("a", "b", "n", F.col("rep").alias("copy_id"), F.coalesce("root", "rep").alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links")))
    return signed.select("doc_id", "a", "b", "n").join(of_class, ["a", "b", "n"]).select("doc_id", "copy_id", F.when(F.col("doc_id").isNotNull(), F.col("class_id")).alias("class_id"), "n_links")


def jaccard_join(docs: DataFrame, n: int = 5, similarity: float = 0.8, recall: float = 0.999, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """(members, links).

    members: doc_id, copy_id (least id with the same n-gram set), class_id (least id of the near-duplicate class), n_links
    (other n-gram sets at or over the similarity to the document's own).
    links: all verified pairs (x, y, jaccard) of representatives, x < y.
    """
    space, signed, classes, sets, roots = _near(docs, n, similarity, recall, id_col, text_col)
    units = _units(space, roots, sets)
    degree = _per_unit(units, similarity, pairs=False).groupBy("node").agg(F.sum("n_links").alias("n_links"))
    return _label(space, signed, classes, roots.join(degree, "node")), _per_unit(units, similarity, pairs=True)


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The documents with one of each near-duplicate class left: the least id. Links inside classes are not needed for that."""
    space, signed, classes, _, roots = _near(docs, **options)
    members = _label(space, signed, classes, roots.withColumn("n_links", F.lit(None).cast("long")))
    name = unused("_gone", docs)
    gone = members.filter("doc_id <> class_id").select(F.col("doc_id").alias(name)).distinct()
    return docs.join(gone.hint("shuffle_hash"), F.col(options.get("id_col", "doc_id")) == F.col(name), "left_anti")
