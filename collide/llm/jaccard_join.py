"""Exact Jaccard join of word-shingle sets, with count vectors in an R-tree.

Tokens are hashed into groups. Two sets that link differ in few tokens, so with more groups than that at least one group
holds the same tokens in both: sets that share a group's content meet in a block. In a block each set is a point, the
numbers of its tokens in a fixed number of groups; an R-tree's boxes bound the overlap of a set with all points inside by
the sum of the smaller coordinates, and what survives is verified on the sets themselves. Links are kept as a spanning
forest: a pair is tested only while its two sets are not yet in one component, so groups of copies cost no pairs.

Defined results: a null text is an empty one; a text without words has an empty set, linked with nothing; rows with the
same set are linked, repeated rows included; a null doc_id is no candidate for a component's smallest id (a component of
such rows alone has a null id); an empty table gives an empty result; a very long text is one set like any other, compared
whole; other columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .graph import components
from .repeats import RangeHash

#: Members of one shared-group run that are named by what they are; a longer run goes on under its own name.
RUN = 1 << 18
#: Bytes of sets compared in one go; larger blocks are dealt in tiles, each pair of tiles a unit of work.
TILE_BYTES = 24 << 20
_K = np.uint64(0x9E3779B97F4A7C15)


@dataclass(frozen=True)
class Plan:
    """Words per shingle, threshold num/den, and the size classes with their numbers of groups."""

    shingle: int
    num: int
    den: int
    ratio: float = 1.3
    bounds: np.ndarray = field(init=False, repr=False, compare=False)

    def __post_init__(self):
        b = [1]
        while b[-1] < 1 << 40:
            b.append(max(b[-1] + 1, int(b[-1] * max(self.ratio, 1.1 * self.den / self.num))))
        object.__setattr__(self, "bounds", np.array(b, dtype=np.int64))

    def level(self, n: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.bounds, n, side="right") - 1

    def groups(self, level: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Number of groups, and the spare ones among them, at a level whose larger sets are of that class. Linked sets differ in
        at most `differ` tokens, so at least one group more than `spare` is equal in both. A set leaves its empty groups unnamed
        if they are no more than `spare`; it then shares at least one more than the rest of `spare` with each set it links with."""
        most = 2 * (self.bounds[level + 1] - 1)
        differ = most * (self.den - self.num) // (self.den + self.num)
        spare = np.where(differ > 0, 1 + differ * 15 // 100, 0)
        return differ + 1 + spare, spare

    def need(self, a, b):
        """Least overlap of linked sets of sizes a and b."""
        return -(-(self.num * (a + b)) // (self.num + self.den))


def shingle_sets(texts: list[str], size: int) -> tuple[np.ndarray, np.ndarray]:
    """(document, hash) of all distinct shingles, sorted."""
    words: list[bytes] = []
    sizes = []
    for t in texts:
        w = t.encode("utf-8", "surrogatepass").lower().split()
        words += w
        sizes.append(len(w))
    n = np.array(sizes, dtype=np.int64)
    begin = np.cumsum(n) - n
    hashes = RangeHash(common.word_hashes(words))
    doc = np.repeat(np.arange(len(n)), np.maximum(n - size + 1, (n > 0).astype(np.int64)))
    first = np.arange(len(doc)) - np.repeat(np.cumsum(np.bincount(doc, minlength=len(n))) - np.bincount(doc, minlength=len(n)), np.bincount(doc, minlength=len(n)))
    s = begin[doc] + first
    h = hashes(s, s + np.minimum(size, n[doc]))
    order = np.lexsort((h, doc))
    doc, h = doc[order], h[order]
    new = np.ones(len(h), dtype=bool)
    new[1:] = (doc[1:] != doc[:-1]) | (h[1:] != h[:-1])
    return doc[new], h[new]


def _set_keys(doc: np.ndarray, h: np.ndarray, docs: int) -> tuple[np.ndarray, np.ndarray]:
    n = np.bincount(doc, minlength=docs)
    total = np.zeros(docs, dtype=np.uint64)
    np.add.at(total, doc, common.mix(h * _K))
    return common.mix(total + n.astype(np.uint64) * _K), n


#: Rows of documents have n below zero (minus one, minus the set's size), their key as sig, and their id as extra. Rows of named
#: groups have as extra twice the least number of shared groups of a link at this level, plus one at the upper level.
_ROWS = "sig long, setkey long, n int, extra long"
_NAMES = ["sig", "setkey", "n", "extra"]
_FOUND = "block long, setkey long, n int, extra long, times int"


def _rows(*columns) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int32())[: len(columns)]
    names = _NAMES if len(columns) == 4 else ["block", "setkey", "n", "extra", "times"]
    return pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x, t) for x, t in zip(columns, kinds, strict=True)], names)


def _signatures(plan: Plan):
    """Rows of documents and of the named groups of each distinct set."""

    def named(doc: np.ndarray, h: np.ndarray, n: np.ndarray, level: np.ndarray, which: np.ndarray) -> tuple[np.ndarray, ...]:
        """Names of the groups, at `level`, of the sets `which`; their sets; and how many a link of theirs shares at least."""
        groups, spare = plan.groups(level)
        at = np.cumsum(groups) - groups
        place = np.full(len(n), -1, dtype=np.int64)
        place[which] = np.arange(len(which))
        mine = place[doc] >= 0
        x, d = common.mix(h[mine] + _K), place[doc[mine]]
        slot = at[d] + (x % groups[d].astype(np.uint64)).astype(np.int64)
        total = int(groups.sum())
        content = np.zeros(total, dtype=np.uint64)
        np.add.at(content, slot, common.mix(x))
        empty = np.bincount(slot, minlength=total) == 0
        owner = np.repeat(np.arange(len(which)), groups)
        empties = np.bincount(owner[empty], minlength=len(which))
        go = ~empty | (empties > spare)[owner]
        least = 1 + np.maximum(spare - empties, 0)
        inside = np.arange(total) - at[owner]
        name = common.mix(content + common.mix((inside + (level[owner] << 40)).astype(np.uint64) + _K))
        return name[go], which[owner[go]], least[owner[go]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            doc, h = shingle_sets(list(common.texts(b)), plan.shingle)
            key, n = _set_keys(doc, h, b.num_rows)
            yield _rows(b.column("key"), common.signed(key), -1 - n, b.column("doc_id"))
            _, one = np.unique(key, return_index=True)
            one = one[n[one] > 0]
            level = plan.level(n[one])
            upper = plan.den * n[one] >= plan.num * plan.bounds[level + 1]
            for up, lv, which in ((0, level, one), (1, level[upper] + 1, one[upper])):
                name, owner, least = named(doc, h, n, lv, which)
                yield _rows(common.signed(name), common.signed(key[owner]), n[owner], 2 * least + up)

    return run


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sorted by sig and set: runs of several sets become blocks, named by their members, so that equal blocks get equal names;
    `times` counts them. A run longer than RUN goes on under its own name, so nothing unbounded is held."""
    held: list[np.ndarray] | None = None
    streaming: int | None = None
    kept: list[tuple] = []

    def close(c: list[np.ndarray]) -> tuple | None:
        """Blocks of complete runs."""
        sig, key = c[0], c[1]
        new = np.ones(len(sig), dtype=bool)
        new[1:] = sig[1:] != sig[:-1]
        distinct = new.copy()
        distinct[1:] |= key[1:] != key[:-1]
        sig, key, n, extra = (x[distinct] for x in c)
        at = np.flatnonzero(new[distinct])
        size = np.diff(np.append(at, len(sig)))
        if not (size > 1).any():
            return None
        total = np.add.reduceat(common.mix(key.view(np.uint64) * _K), at)
        name = np.repeat(common.mix(total + size.astype(np.uint64)).view(np.int64), size)
        go = np.repeat(size > 1, size)
        return name[go], key[go], n[go], extra[go]

    def flush() -> pa.RecordBatch:
        name, key, n, extra = (np.concatenate(x) for x in zip(*kept, strict=True))
        kept.clear()
        order = np.lexsort((extra, key, name))
        name, key, n, extra = name[order], key[order], n[order], extra[order]
        new = np.ones(len(name), dtype=bool)
        new[1:] = (name[1:] != name[:-1]) | (key[1:] != key[:-1]) | (extra[1:] != extra[:-1])
        at = np.flatnonzero(new)
        return _rows(name[at], key[at], n[at], extra[at], np.diff(np.append(at, len(name))))

    for b in batches:
        c = [b.column(i).to_numpy(zero_copy_only=False) for i in range(3)]
        docs = c[2] < 0
        if docs.any():
            d = b.filter(pa.array(docs))
            yield _rows(d.column(0), d.column(1), d.column(2), d.column(3), np.zeros(d.num_rows))
        c.append(b.column(3).fill_null(0).to_numpy(zero_copy_only=False))
        c = [x[~docs] for x in c]
        if streaming is not None and len(c[0]):
            more = c[0] == streaming
            if more.any():
                kept.append(tuple(x[more] for x in c))
                c = [x[~more] for x in c]
            if len(c[0]):
                streaming = None
        if len(c[0]):
            if held is not None:
                c = [np.concatenate(x) for x in zip(held, c, strict=True)]
            last = int(np.searchsorted(c[0], c[0][-1]))
            held = None
            if last and (out := close([x[:last] for x in c])):
                kept.append(out)
            if len(c[0]) - last > RUN:
                kept.append(tuple(x[last:] for x in c))
                streaming = int(c[0][-1])
            else:
                held = [x[last:].copy() for x in c]
        if sum(len(k[0]) for k in kept) > RUN:
            yield flush()
    if held is not None and (out := close(held)):
        kept.append(out)
    if kept:
        yield flush()


_SETS = "setkey long, n int, counts binary, tokens binary"


def _sets(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            doc, h = shingle_sets(list(common.texts(b)), shingle)
            key, n = _set_keys(doc, h, b.num_rows)
            sets = np.split(h, np.cumsum(n)[:-1])
            counts = [count_vector(x).tobytes() for x in sets]
            yield pa.RecordBatch.from_arrays([pa.array(common.signed(key)), pa.array(n, pa.int32()), pa.array(counts, pa.binary()), pa.array([x.tobytes() for x in sets], pa.binary())], ["setkey", "n", "counts", "tokens"])

    return run


def dims_for(n: int) -> int:
    """Groups that are counted, the dimensions of a point: a power of two with one to two tokens a group."""
    return min(1 << 16, max(16, 1 << max(0, (int(n) - 1) // 2).bit_length()))


def count_vector(tokens: np.ndarray) -> np.ndarray:
    """How many of a set's tokens fall into each group; groups are split further until a count fits a byte."""
    dims = dims_for(len(tokens))
    while True:
        out = np.bincount((common.mix(tokens) & np.uint64(dims - 1)).astype(np.int64), minlength=dims)
        if out.max(initial=0) < 256:
            return out.astype(np.uint8)
        dims *= 2


def points_of(counts: list[np.ndarray]) -> np.ndarray:
    """Points of one number of dimensions: groups are numbered by low bits, so finer counts fold into coarser ones."""
    dims = min(map(len, counts))
    return np.stack([c if len(c) == dims else c.reshape(-1, dims).sum(axis=0, dtype=np.uint16) for c in counts]).astype(np.uint16)


class CountTree:
    """Points of token counts in an R-tree. A box's upper corner bounds the overlap with every point below it, and its least set
    size the overlap that a link needs; a search descends from the top into boxes that may hold a link."""

    LEAF, FAN = 16, 8

    def __init__(self, points: np.ndarray, n: np.ndarray, plan: Plan):
        self.plan, self.n, self.points = plan, n.astype(np.int64), points
        order = np.lexsort((points[:, 0], self.n))
        # sort-tile: slices by size, then by the coordinate that varies most within the slice
        tiles = []
        for at in range(0, len(order), self.LEAF * self.FAN):
            part = order[at : at + self.LEAF * self.FAN]
            tiles.append(part[np.argsort(points[part, int(np.argmax(points[part].var(axis=0)))], kind="stable")])
        self.order = np.concatenate(tiles) if tiles else order
        #: From the leaves up: upper corners and least sizes of the nodes; a node's children lie side by side below it.
        self.levels: list[tuple[np.ndarray, np.ndarray]] = []
        upper, least, fan = points[self.order], self.n[self.order], self.LEAF
        while not self.levels or len(least) > self.FAN:
            at = np.arange(0, len(least), fan)
            upper, least, fan = np.maximum.reduceat(upper, at, axis=0), np.minimum.reduceat(least, at), self.FAN
            self.levels.append((upper, least))

    def near(self, i: int) -> np.ndarray:
        """Points whose bound on the overlap with point i allows a link, the most promising first."""
        p, n = self.points[i], int(self.n[i])
        nodes = np.arange(len(self.levels[-1][1]))
        self.visited = 0
        for depth in range(len(self.levels) - 1, -1, -1):
            upper, least = self.levels[depth]
            self.visited += len(nodes)
            nodes = nodes[np.minimum(upper[nodes], p).sum(axis=1, dtype=np.int64) >= self.plan.need(least[nodes], n)]
            fan, below = (self.FAN, len(self.levels[depth - 1][1])) if depth else (self.LEAF, len(self.order))
            nodes = (nodes[:, None] * fan + np.arange(fan)).reshape(-1)
            nodes = nodes[nodes < below]
        found = self.order[nodes]
        self.visited += len(found)
        bound = np.minimum(self.points[found], p).sum(axis=1, dtype=np.int64)
        ok = bound >= self.plan.need(self.n[found], n)
        found, bound = found[ok], bound[ok]
        return found[np.argsort(-bound, kind="stable")]


def spanning_links(sets: list[np.ndarray], group: list[int], side: list[int] | None, plan: Plan) -> list[tuple[int, int]]:
    """Verified links that join sets of different groups; enough of them to connect all that link. side: only 0 with 1."""
    root = {g: g for g in group}

    def top(g: int) -> int:
        while root[g] != g:
            root[g] = root[root[g]]
            g = root[g]
        return g

    tree = CountTree(points_of([count_vector(x) for x in sets]), np.array([len(x) for x in sets]), plan)
    links = []
    apart = len(root)
    for i in range(len(sets)):
        for j in tree.near(i).tolist():
            if j == i or (side is not None and side[i] == side[j]):
                continue
            a, b = top(group[i]), top(group[j])
            if a == b:
                continue
            both = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
            if plan.den * both >= plan.num * (len(sets[i]) + len(sets[j]) - both):
                root[a] = b
                links.append((i, j))
                apart -= 1
                if apart == 1:
                    return links
    return links


def _by_unit(names: list[str], unit, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (block, i, j); `unit` turns each unit's rows into rows of long columns."""
    rows: list[tuple] = []

    def batch(out: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], pa.int64()) for k in range(len(names))], names)

    for b in batches:
        out: list[tuple] = []
        for r in zip(*(c.to_pylist() for c in b.columns), strict=True):
            if rows and r[:3] != rows[0][:3]:
                out += unit(rows)
                rows = []
            rows.append(r)
        yield batch(out)
    if rows:
        yield batch(unit(rows))


def _verify(plan: Plan):
    """Verified links of each unit."""

    def unit(rows: list[tuple]) -> list[tuple]:
        if len({r[3] for r in rows}) < 2:
            return []
        sets = [np.frombuffer(r[6], dtype=np.uint64) for r in rows]
        i, j = rows[0][1], rows[0][2]
        found = spanning_links(sets, [r[3] for r in rows], [int(r[5] == j) for r in rows] if i != j else None, plan)
        return [(rows[a][4], rows[b][4]) for a, b in found]

    return lambda batches: _by_unit(["a", "b"], unit, batches)


def _near(plan: Plan, best: bool):
    """Sets of different components whose counts allow a link, named by the two components. With `best` each set names only the
    most promising other set of its block."""

    def unit(rows: list[tuple]) -> list[tuple]:
        group = np.array([r[3] for r in rows], dtype=np.int64)
        if (group == group[0]).all():
            return []
        n = np.array([r[6] for r in rows], dtype=np.int64)
        tree = CountTree(points_of([np.frombuffer(r[7], dtype=np.uint8) for r in rows]), n, plan)
        tile, apart = np.array([r[5] for r in rows]), rows[0][1] != rows[0][2]
        out: set[tuple] = set()
        for x in range(len(rows)):
            y = tree.near(x)
            y = y[(group[y] != group[x]) & ((tile[y] != tile[x]) | (not apart))]
            y = y[:1] if best else y[group[y] < group[x]]
            for k in y.tolist():
                pair = (min(int(group[k]), int(group[x])), max(int(group[k]), int(group[x])))
                out.add((*pair, rows[x][4], rows[x][6]))
                out.add((*pair, rows[k][4], rows[k][6]))
        return list(out)

    return lambda batches: _by_unit(["lo", "hi", "setkey", "n"], unit, batches)


def _units(members: DataFrame, groups: DataFrame | None, weight: str) -> DataFrame:
    """block, i, j, grp, setkey, tile: members (block, setkey, n) dealt to units of work. Blocks of more than TILE_BYTES
    (`weight` per member) are cut in tiles, and every pair of tiles is a unit, so no pair is missed and no unit is large."""
    if groups is None:
        known = members.withColumn("grp", F.col("setkey"))
    else:
        known = members.join(groups.select(F.col("node").alias("setkey"), "component"), "setkey", "left").withColumn("grp", F.coalesce("component", "setkey")).drop("component")
    tiles = members.groupBy("block").agg(F.greatest(F.lit(1), F.ceil(F.sum(F.expr(weight)) / F.lit(TILE_BYTES))).cast("int").alias("tiles"))
    known = known.join(tiles, "block").withColumn("tile", F.pmod(F.xxhash64("setkey"), F.col("tiles")).cast("int"))
    pairs = F.transform(F.sequence(F.lit(0), F.col("tiles") - 1), lambda o: F.struct(F.least(o, F.col("tile")).alias("i"), F.greatest(o, F.col("tile")).alias("j")))
    return known.select("block", "setkey", "grp", "tile", F.explode(pairs).alias("p")).select("block", F.col("p.i").alias("i"), F.col("p.j").alias("j"), "grp", "setkey", "tile")


def _sorted_units(units: DataFrame) -> DataFrame:
    return units.repartition("block", "i", "j").sortWithinPartitions("block", "i", "j")


def _links(members: DataFrame, sets: DataFrame, groups: DataFrame | None, plan: Plan) -> DataFrame:
    """Verified links among the members of each block, enough to connect what links."""
    units = _units(members, groups, "8L * n").join(sets.select("setkey", "tokens"), "setkey").select("block", "i", "j", "grp", "setkey", "tile", "tokens")
    return common.materialise(_sorted_units(units).mapInArrow(_verify(plan), "a long, b long"))


def _pairs_of_groups(members: DataFrame, sets: DataFrame, groups: DataFrame, plan: Plan, best: bool) -> DataFrame:
    """block, setkey, n: per pair of components that may link, the sets that may do it. Counts alone are sent, not sets."""
    units = _units(members, groups, "n + 96L").join(sets.select("setkey", "n", "counts"), "setkey").select("block", "i", "j", "grp", "setkey", "tile", "n", "counts")
    near = _sorted_units(units).mapInArrow(_near(plan, best), "lo long, hi long, setkey long, n long").distinct()
    return common.materialise(near.select(F.xxhash64("lo", "hi").alias("block"), "setkey", "n"))


def linked(docs: DataFrame, shingle: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """doc_id, key, class, n_shingles, component_id: a row per row of docs; component_id is the smallest doc_id reachable by links."""
    spark = docs.sparkSession
    common.ship(spark)
    plan = Plan(shingle, num, den)
    k = common.keyed(docs).withColumn("doc_id", F.col("doc_id").cast("long"))
    met = common.materialise(k.mapInArrow(_signatures(plan), _ROWS).repartition("sig").sortWithinPartitions("sig", "setkey").mapInArrow(_blocks, _FOUND))
    rows = met.where("n < 0").select(F.col("extra").alias("doc_id"), F.col("block").alias("key"), "setkey", (-1 - F.col("n")).cast("long").alias("n_shingles"))
    # a link shares many groups: sets that share fewer with all others together have none
    shared = met.where("n >= 0").groupBy("setkey", "extra").agg(F.sum("times").alias("all")).where(F.col("all") >= F.shiftright("extra", 1)).select("setkey", "extra")
    able = met.where("n >= 0").join(shared, ["setkey", "extra"], "left_semi").groupBy("block", "setkey").agg(F.max("n").alias("n"))
    able = common.materialise(able)
    several = able.groupBy("block").agg(F.count(F.lit(1)).alias("members")).where("members > 1").select("block")
    blocks = common.materialise(able.join(several, "block", "left_semi"))

    # the sets that meet any other, each once
    active = blocks.select("setkey").distinct()
    chosen = rows.join(active, "setkey", "left_semi").groupBy("setkey").agg(F.min("key").alias("key")).select("key")
    sets = common.materialise(k.join(chosen, "key", "left_semi").select("text").mapInArrow(_sets(shingle), _SETS).dropDuplicates(["setkey"]))

    # Three passes, each of which leaves less to the next. Each set in its largest block connects most copies at the cost of one
    # set each. Then every set tries its most promising partner in each block that still holds several components: variants of
    # one text meet the text. The last pass verifies every pair of components whose counts allow a link, each pair once.
    sizes = blocks.groupBy("block").agg(F.count(F.lit(1)).alias("members"))
    largest = blocks.join(sizes, "block").groupBy("setkey", "n").agg(F.max(F.struct("members", "block")).alias("m")).select(F.col("m.block").alias("block"), "setkey", "n")
    links = _links(largest, sets, None, plan)
    groups = components(links)
    for best in (True, False):
        tagged = blocks.join(groups.select(F.col("node").alias("setkey"), "component"), "setkey", "left").withColumn("grp", F.coalesce("component", "setkey"))
        mixed = tagged.groupBy("block").agg(F.min("grp").alias("lo"), F.max("grp").alias("hi")).where("lo <> hi").select("block")
        pairs = _pairs_of_groups(blocks.join(mixed, "block", "left_semi"), sets, groups, plan, best)
        links = links.unionByName(_links(pairs, sets, groups, plan))
        groups = components(links)

    named = rows.join(groups.select(F.col("node").alias("setkey"), "component"), "setkey", "left").withColumn("class", F.coalesce("component", "setkey"))
    named = named.select("doc_id", "key", "n_shingles", "class")
    least = named.groupBy("class").agg(F.min("doc_id").alias("least"))
    full = named.join(least, "class", "left")
    return full.select("doc_id", "key", "class", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("least")).otherwise(F.col("doc_id")).alias("component_id"))


def one_of_each(docs: DataFrame, shingle: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """docs without all but one document of each component, the one of least id; rows that repeat it fully go as well."""
    found = common.materialise(linked(docs, shingle, num, den).select("doc_id", "key", "class", "n_shingles"))
    empty = F.col("n_shingles") == 0
    group = found.where(~empty).groupBy("class").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "key")).alias("m")).select(F.col("m.key").alias("kept_key"))
    kept = group.unionByName(found.where(empty).select(F.col("key").alias("kept_key"))).distinct()
    stay = common.wrapped(docs).join(kept, F.col("key") == F.col("kept_key"), "left_semi")
    if not found.where(~empty).groupBy("key").count().where("count > 1").isEmpty():
        stay = stay.dropDuplicates(["key"])
    return common.unwrapped(stay, docs.columns)


def op7_jaccard_join(spark, sf_dir: str) -> DataFrame:
    """Set size and component of every document; defined results as in the module's docstring."""
    return linked(spark.read.parquet(f"{sf_dir}/documents.parquet"), shingle=4, num=85, den=100).select("doc_id", "n_shingles", "component_id")
