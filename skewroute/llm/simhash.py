"""SimHash near-duplicates with a Gray-order hierarchical index.

Distinct fingerprints are sorted by Gray rank over the whole table and cut into slices of neighbours. Every group of neighbours is
a node that keeps the bits its members agree on (mask, pattern): leaves of ``LEAF`` fingerprints, ``FAN`` nodes under each
upper one up to the slice, and the slices' own nodes with a tree of the same kind above them, which is small enough to send
out (at most ``MAX_SLICES`` slices, 16 bytes each). Two nodes differ at least where both agree on a bit and the bits differ; going
down, bits join the masks and the differences add up, and a pair of nodes is dropped with everything below it once they exceed
the distance. So slices find the slices they may have a link with, and only those meet, dealt by slice; inside, the same
descent goes on to pairs of leaves, whose fingerprints are compared. A meeting gives a spanning forest of its links, never all
its pairs. No task takes more than two slices at a time, however many fingerprints are alike.

The stage of the pipeline also links what three bits of 64 do not reach: texts whose sets of five-word shingles have a
Jaccard similarity of at least 0.8. Banded minimum hashes find the candidates, the sets themselves decide.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skewroute.llm.common import bit_set, bitmap_of, free_shuffles, in_bitmap, join_counted, materialize, read_table, tidy
from skewroute.llm.components import connected_components

SEED = 42
DISTANCE = 3
#: Fingerprints of a slice; more where there would be over ``MAX_SLICES`` of them, so that their nodes are of bounded size.
SLICE = 4096
MAX_SLICES = 1 << 16
LEAF = 4
FAN = 8
#: Pairs of nodes or leaves that are looked at in one go; bounds memory only.
_MEET = 1 << 12
_STEP = 1 << 14
#: Words of a shingle of the stage, and the similarity that links, as a fraction.
SET_SHINGLE = 5
JACCARD = (4, 5)
#: A pair at similarity s has no band in common with probability (1 - s**BAND_ROWS)**BANDS: 3e-6 at 0.8.
BANDS, BAND_ROWS = 32, 5


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """Unsigned 64-bit SimHash over word shingles (repeats counted, ASCII lower-cased); no words: 0."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    if len(words) <= shingle:
        return digest(b" ".join(words), SEED)
    grams = [b" ".join(g) for g in zip(*(words[i:] for i in range(shingle)), strict=False)]
    ones = np.zeros(64, np.int64)
    for i in range(0, len(grams), _STEP):
        h = np.fromiter((digest(g, SEED) for g in grams[i : i + _STEP]), np.uint64)
        ones += np.unpackbits(h.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(grams), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """``(doc_id, k, r, fp)``, all long, one row per input row; ``k`` and ``r`` tell rows with one id apart.

    The text never leaves the scanning task.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.fromiter((fingerprint(t, shingle) for t in b.column("t").to_pylist()), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("i", "k", "r")), pa.array(fp.view(np.int64))], ["doc_id", "k", "r", "fp"])

    source = docs.select(F.col(id_col).cast("long").alias("i"), *_row_key(id_col, text_col), F.col(text_col).alias("t"))
    return source.mapInArrow(tidy(run), "doc_id long, k long, r long, fp long")


def shingle_set(text: str | None, shingle: int = SET_SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of a text's word shingles (ASCII lower-cased); a shorter text is one shingle, no words none."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    grams = {b" ".join(g) for g in zip(*(words[i:] for i in range(shingle)), strict=False)} or ({b" ".join(words)} if words else set())
    return np.unique(np.fromiter((xxhash.xxh64_intdigest(g, SEED) for g in grams), np.uint64, len(grams)))


_SPREAD = np.random.default_rng(SEED).integers(0, 1 << 63, (2, BANDS * BAND_ROWS), dtype=np.uint64) | np.array([[1], [0]], np.uint64)


def bands(grams: np.ndarray) -> np.ndarray:
    """A hash of each band of minimum hashes; equal bands make two sets candidates."""
    least = np.full(BANDS * BAND_ROWS, np.iinfo(np.uint64).max)
    for i in range(0, len(grams), 2048):
        x = grams[None, i : i + 2048] * _SPREAD[0][:, None] + _SPREAD[1][:, None]
        # A product's low bits know only the low bits of its factors; the upper half is folded in.
        np.minimum(least, ((x ^ x >> np.uint64(32)) * np.uint64(0x9E3779B97F4A7C15)).min(axis=1), out=least)
    rows = np.ascontiguousarray(least.reshape(BANDS, BAND_ROWS))
    return np.fromiter((xxhash.xxh64_intdigest(r.tobytes(), k) for k, r in enumerate(rows)), np.uint64, BANDS)


def _set_hash(grams: np.ndarray) -> int:
    return int(np.int64(np.uint64(xxhash.xxh64_intdigest(grams.tobytes(), SEED))))


def _signatures(docs: DataFrame) -> DataFrame:
    """``(doc_id, k, r, fp, n, m, bands)``: also a hash of the shingle set, its size and its bands, null for texts without words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column("t").to_pylist()
            fp = np.fromiter((fingerprint(t) for t in texts), np.uint64, b.num_rows)
            sets = [shingle_set(t) for t in texts]
            n, m = pa.array([_set_hash(s) if len(s) else None for s in sets], pa.int64()), pa.array([len(s) or None for s in sets], pa.int32())
            band = pa.array([bands(s).view(np.int64) if len(s) else None for s in sets], pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("doc_id", "k", "r")), pa.array(fp.view(np.int64)), n, m, band], ["doc_id", "k", "r", "fp", "n", "m", "bands"])

    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *_row_key("doc_id", "text"), F.col("text").alias("t"))
    return source.mapInArrow(tidy(run), "doc_id long, k long, r long, fp long, n long, m int, bands array<long>")


def _sets_of(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """``(n, grams)`` of the shingle sets ``wanted(n, k, r)``, each from one row that has it; other texts are passed over."""
    shared = bitmap_of(wanted.select(F.xxhash64("k", "r").alias("a")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            seen: dict[int, np.ndarray] = {}
            for t in b.filter(pa.array(bit_set(shared.value, b.column("a").to_numpy().view(np.uint64)))).column("t").to_pylist():
                if len(grams := shingle_set(t)):
                    seen.setdefault(_set_hash(grams), grams)
            if seen:
                ends = np.cumsum([0, *map(len, seen.values())]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.int64()), pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(list(seen.values())).view(np.int64)))], ["n", "grams"])

    k, r = _row_key("doc_id", "text")
    found = docs.select(F.xxhash64(k, r).alias("a"), F.col("text").alias("t")).mapInArrow(tidy(run), "n long, grams array<long>")
    return materialize(found.join(wanted.select("n"), "n", "left_semi").dropDuplicates(["n"]), "sets")


def _similar(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Those of the pairs ``(u, v)`` whose ``sets(n, grams)`` reach the similarity. ``u`` may be in many pairs, ``v`` in few."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            (xs, x_at), (ys, y_at) = ((c.values.to_numpy().view(np.uint64), c.offsets.to_numpy()) for c in (b.column("x"), b.column("y")))
            hit = np.zeros(b.num_rows, bool)
            for i in range(b.num_rows):
                x, y = xs[x_at[i] : x_at[i + 1]], ys[y_at[i] : y_at[i + 1]]
                both = len(np.intersect1d(x, y, assume_unique=True))
                hit[i] = both * JACCARD[1] >= (len(x) + len(y) - both) * JACCARD[0]
            yield pa.RecordBatch.from_arrays([b.column("u"), b.column("v")], ["u", "v"]).filter(pa.array(hit, pa.bool_()))

    pairs = materialize(pairs, "pairs")
    many = pairs.groupBy("u").agg(F.count("*").alias("c"))
    left = sets.select(F.col("n").alias("u"), F.col("grams").alias("x")).join(many, "u")
    half = pairs.join(sets.select(F.col("n").alias("v"), F.col("grams").alias("y")), "v")
    held = join_counted(half, left, ["u"], pairs.count(), F.size("x") <= 2048)
    return materialize(held.select("u", "v", "x", "y").mapInArrow(tidy(run), "u long, v long"), "near")


def _fits(low, high):
    """Whether sets of these sizes can be similar at all."""
    return low * JACCARD[1] >= high * JACCARD[0]


def _set_classes(docs: DataFrame, prints: DataFrame) -> DataFrame:
    """``(node, root)`` of the shingle sets that links connect: every pair with a band in common is settled, most without being met.

    In each bucket all sets are first held against its hub, the set that meets most others over all bands: near copies of one text meet
    that text. What is left are buckets with sets of several components. There a shingle counts for a set only if a set of
    another component has it too: with ``s`` such shingles at most ``s`` can be in common, which rules out most sets by themselves, and most
    pairs by their sizes. Pairs that no bound rules out are compared.
    """
    nodes = materialize(prints.where("n IS NOT NULL").groupBy("n").agg(F.first("m").alias("m"), F.first("bands").alias("bands"), F.min(F.struct("k", "r")).alias("x")), "nodes")
    routed = nodes.select("n", "m", F.explode("bands").alias("b"))
    sizes = materialize(routed.groupBy("b").agg(F.count("*").alias("c")).where("c > 1"), "sizes")
    # Most bands are one set's alone: a bitmap of the others thins them before they are joined.
    met = in_bitmap(routed, bitmap_of(sizes, key="b"), "b")
    shared = materialize(join_counted(met, sizes, ["b"], sizes.agg(F.sum("c")).first()[0] or 0), "buckets")
    total = shared.count()
    popular = shared.groupBy("n").agg(F.sum("c").alias("pop"))
    hubs = shared.join(popular, "n").groupBy("b").agg(F.max(F.struct("pop", "n", "m")).alias("h"), F.first("c").alias("c")).select("b", "c", F.col("h.n").alias("hub"), F.col("h.m").alias("hub_m"))
    met = join_counted(shared.drop("c"), materialize(hubs, "hubs"), ["b"], total)
    first = met.where((F.col("n") != F.col("hub")) & _fits(F.least("m", "hub_m"), F.greatest("m", "hub_m"))).select(F.col("hub").alias("u"), F.col("n").alias("v")).distinct()
    wanted = nodes.join(shared.select("n").distinct(), "n", "left_semi").select("n", F.col("x.k").alias("k"), F.col("x.r").alias("r"))
    sets = _sets_of(docs, wanted)
    near = _similar(first, sets)
    roots = materialize(connected_components(near), "roots")
    free_shuffles(docs.sparkSession)
    told = materialize(shared.drop("c").join(roots.withColumnRenamed("node", "n"), "n", "left").select("b", "n", "m", F.coalesce("root", "n").alias("root")), "told")
    return connected_components(near.unionByName(_similar(_across(_open(told), sets), sets)))


def _open(told: DataFrame) -> DataFrame:
    """Rows ``(b, n, m, root, ...)`` of buckets with several components."""
    several = told.groupBy("b").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count("*").alias("c")).where("lo <> hi").select("b", "c")
    several = materialize(several, "several")
    return materialize(join_counted(told, several, ["b"], several.agg(F.sum("c")).first()[0] or 0).drop("c"), "open")


def _across(rest: DataFrame, sets: DataFrame) -> DataFrame:
    """Pairs ``(u, v)`` of different components that share a bucket and that no bound rules out."""
    each = rest.select("n", "root").distinct().join(sets, "n").select("n", "root", F.explode("grams").alias("g"))
    each = materialize(each, "grams")
    contested = materialize(each.groupBy("g").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count("*").alias("c")).where("lo <> hi").select("g", "c"), "contested")
    held = join_counted(each.select("n", "g"), contested, ["g"], each.count()).groupBy("n").agg(F.count("*").cast("int").alias("s"))
    # A set is out if even all of another one lay within what it may share; and out of a bucket if the least set there is too large for it.
    left = rest.join(held, "n").where(_fits(F.col("s"), F.col("m")))
    least = materialize(left.groupBy("b").agg(F.min("m").alias("lm"), F.count("*").alias("c")), "least")
    left = materialize(join_counted(materialize(left, "left"), least, ["b"], rest.count()).where(_fits(F.col("s"), F.col("m") + F.col("lm") - F.col("s"))).drop("lm", "c"), "left")
    a, b = (_open(left).select("b", *(F.col(c).alias(c + t) for c in ("n", "m", "s", "root"))) for t in "xy")
    s = F.least("sx", "sy")
    return a.join(b, "b").where((F.col("nx") < F.col("ny")) & (F.col("rootx") != F.col("rooty")) & _fits(s, F.col("mx") + F.col("my") - s)).select(F.col("nx").alias("u"), F.col("ny").alias("v")).distinct()


def _row_key(id_col: str, text_col: str) -> tuple:
    return F.xxhash64(id_col, text_col).alias("k"), F.xxhash64(text_col).alias("r")


def gray_rank(fp: np.ndarray) -> np.ndarray:
    """Position of each bit pattern in the reflected Gray code sequence."""
    g = fp.astype(np.uint64).copy()
    for s in (1, 2, 4, 8, 16, 32):
        g ^= g >> np.uint64(s)
    return g


def _gray_rank_col(c):
    for s in (1, 2, 4, 8, 16, 32):
        c = c.bitwiseXOR(F.shiftrightunsigned(c, s))
    return c


Nodes = tuple[np.ndarray, np.ndarray]


def _nodes(low: np.ndarray, high: np.ndarray, width: int) -> Nodes:
    """Common ones and all ones of consecutive groups: bits equal in both are the node's mask, and there they are its pattern."""
    at = np.arange(0, len(low), width)
    return np.bitwise_and.reduceat(low, at), np.bitwise_or.reduceat(high, at)


def _tree(low: np.ndarray, high: np.ndarray, width: int) -> list[Nodes]:
    """Levels of nodes over members in Gray order, lowest first, until ``FAN`` or fewer are left."""
    levels = [_nodes(low, high, width)]
    while len(levels[-1][0]) > FAN:
        levels.append(_nodes(*levels[-1], FAN))
    return levels


def _apart(a: Nodes, i: np.ndarray, b: Nodes, j: np.ndarray) -> np.ndarray:
    """On how many bits all members of node i differ from all members of node j: the differences added up down to them."""
    agreed = ~(a[0][i] ^ a[1][i]) & ~(b[0][j] ^ b[1][j])
    return np.bitwise_count((a[0][i] ^ b[0][j]) & agreed)


class GrayIndex:
    """Nodes over the fingerprints of one slice in Gray order. Counts the pairs of nodes it looks at and drops."""

    def __init__(self, fps: np.ndarray, ordered: bool = False):
        self.fps = fps if ordered else fps[np.argsort(gray_rank(fps), kind="stable")]
        self.levels = _tree(self.fps, self.fps, LEAF)
        self.visited = self.pruned = self.compared = 0

    @property
    def leaf(self) -> Nodes:
        return self.levels[0]

    def leaf_pairs(self, other: GrayIndex, distance: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs of leaves that may hold a link, some thousand at a time; within one index each pair once."""
        own, top = other is self, min(len(self.levels), len(other.levels)) - 1
        i, j = (x.ravel() for x in np.indices((len(self.levels[top][0]), len(other.levels[top][0]))))
        todo = [(top, i[i <= j], j[i <= j]) if own else (top, i, j)]
        while todo:
            level, i, j = todo.pop()
            if len(i) > _MEET:
                todo.append((level, i[_MEET:], j[_MEET:]))
                i, j = i[:_MEET], j[:_MEET]
            stay = _apart(self.levels[level], i, other.levels[level], j) <= distance
            self.visited += len(i)
            i, j = i[stay], j[stay]
            self.pruned += len(stay) - len(i)
            if not len(i):
                continue
            if not level:
                yield i, j
                continue
            x = (i[:, None, None] * FAN + np.arange(FAN)[None, :, None] + np.zeros(FAN, np.int64)).ravel()
            y = (j[:, None, None] * FAN + np.arange(FAN)[None, None, :] + np.zeros((FAN, 1), np.int64)).ravel()
            there = (x < len(self.levels[level - 1][0])) & (y < len(other.levels[level - 1][0]))
            if own:
                there &= x <= y
            todo.append((level - 1, x[there], y[there]))

    def blocks(self, other: GrayIndex, distance: int) -> Iterator[tuple[slice, slice]]:
        """The same as places of the fingerprints."""
        for i, j in self.leaf_pairs(other, distance):
            for x, y in zip(i.tolist(), j.tolist(), strict=True):
                yield slice(x * LEAF, (x + 1) * LEAF), slice(y * LEAF, (y + 1) * LEAF)

    def rows(self) -> np.ndarray:
        """One row a leaf; the last one is filled up with its last fingerprint."""
        n = len(self.fps)
        return self.fps[np.minimum(np.arange(-(-n // LEAF) * LEAF), n - 1)].reshape(-1, LEAF)


def meet(a: GrayIndex, b: GrayIndex, distance: int) -> list[tuple[int, int]]:
    """Edges of a spanning forest of the links within an index (``b`` is ``a``) or between two."""
    shift = 0 if b is a else len(a.fps)
    label, edges = np.arange(shift + len(b.fps)), []
    left, right = a.rows(), b.rows()
    step = _MEET * 64 // LEAF**2
    for i, j in a.leaf_pairs(b, distance):
        for k in range(0, len(i), step):
            x, y = i[k : k + step], j[k : k + step]
            a.compared += len(x) * LEAF**2
            at, p, q = np.nonzero(np.bitwise_count(left[x][:, :, None] ^ right[y][:, None, :]) <= distance)
            # Places beyond the end repeat the last fingerprint.
            u = np.minimum(x[at] * LEAF + p, len(a.fps) - 1)
            v = np.minimum(y[at] * LEAF + q, len(b.fps) - 1) + shift
            while len(u):
                open_ = label[u] != label[v]
                u, v = u[open_], v[open_]
                for s, t in zip(u[:64].tolist(), v[:64].tolist(), strict=True):
                    if label[s] != label[t]:
                        label[label == label[t]] = label[s]
                        edges.append((int(a.fps[s]), int(b.fps[t - shift])))
                u, v = u[64:], v[64:]
    return edges


def forest(left: np.ndarray, right: np.ndarray | None, distance: int) -> list[tuple[int, int]]:
    """``meet`` of bare fingerprints (``right`` None: within ``left``)."""
    a = GrayIndex(left)
    return meet(a, a if right is None else GrayIndex(right), distance)


_LOW = 1 << 63
_SLICED = "g long, lo long, hi long, fps binary"


def _slices(fps: DataFrame, rows: int, parts: int) -> DataFrame:
    """``(g, lo, hi, fps)``: neighbours in Gray order, up to ``rows`` in a slice; ``g`` is the first one's rank as a signed order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(x: np.ndarray) -> pa.RecordBatch:
            first = int(gray_rank(x[:1])[0]) - _LOW
            lo, hi = (int(f.reduce(x).view(np.int64)) for f in (np.bitwise_and, np.bitwise_or))
            return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in ((first, pa.int64()), (lo, pa.int64()), (hi, pa.int64()), (x.tobytes(), pa.binary()))], ["g", "lo", "hi", "fps"])

        held = np.zeros(0, np.uint64)
        for b in batches:
            held = np.r_[held, b.column("fp").to_numpy().view(np.uint64)]
            while len(held) >= rows:
                yield out(held[:rows])
                held = held[rows:]
        if len(held):
            yield out(held)

    ordered = fps.select("fp", _gray_rank_col(F.col("fp")).bitwiseXOR(F.lit(-_LOW)).alias("g")).repartitionByRange(parts, "g").sortWithinPartitions("g")
    return ordered.select("fp").mapInArrow(run, _SLICED)


def _partners(slices: DataFrame, distance: int) -> DataFrame:
    """``(own, other)``: which slices have to meet, each pair once, by descent through the tree over all slices' nodes."""
    nodes = slices.select("g", "lo", "hi").toArrow()
    order = np.argsort(nodes.column("g").to_numpy(), kind="stable")
    g, lo, hi = (nodes.column(c).to_numpy()[order] for c in ("g", "lo", "hi"))
    base = lo.view(np.uint64), hi.view(np.uint64)
    shared = slices.sparkSession.sparkContext.broadcast((g, [base, *_tree(*base, FAN)] if len(g) > FAN else [base]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank, levels = shared.value
        for b in batches:
            for own in b.column("g").to_numpy():
                me = np.searchsorted(rank, own)
                at = np.arange(len(levels[-1][0]))
                for level in range(len(levels) - 1, -1, -1):
                    at = at[_apart(levels[0], np.full(len(at), me), levels[level], at) <= distance]
                    if level:
                        at = (at[:, None] * FAN + np.arange(FAN)).ravel()
                        at = at[at < len(levels[level - 1][0])]
                # Of two slices one is host: by turns the earlier and the later, so that none hosts many more than others.
                at = at[(at == me) | ((at > me) == ((at + me) % 2 == 0))]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), own)), pa.array(rank[at])], ["own", "other"])

    return slices.select("g").mapInArrow(run, "own long, other long")


def _meetings(distance: int):
    """Of rows ``(own, other, fps)`` by host, the host's own first: its links, and a row of what the search looked at."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, host = None, None
        for b in batches:
            edges, counts = [], [0, 0, 0]
            for own, data in zip(b.column("own").to_pylist(), b.column("fps"), strict=True):
                index = GrayIndex(np.frombuffer(data.as_py(), np.uint64), ordered=True)
                if own != now:
                    now, host = own, index
                before = host.visited, host.pruned, host.compared
                edges += meet(host, host if index is host or len(index.fps) == len(host.fps) and (index.fps == host.fps).all() else index, distance)
                counts = [c + x - y for c, x, y in zip(counts, (host.visited, host.pruned, host.compared), before, strict=True)]
            pairs = np.array(edges, np.uint64).reshape(-1, 2).view(np.int64)
            ends = [pa.array([*pairs[:, k].tolist(), None], pa.int64()) for k in (0, 1)]
            yield pa.RecordBatch.from_arrays([*ends, *(pa.array([0] * len(pairs) + [c], pa.int64()) for c in counts)], ["u", "v", "visited", "pruned", "compared"])

    return run


def search(fps: DataFrame, distance: int = DISTANCE, slice_rows: int = SLICE) -> DataFrame:
    """``(u, v, visited, pruned, compared)``, materialised: edges that connect what links connect, and rows without an edge that tell
    how many pairs of nodes were looked at and dropped, and how many pairs of fingerprints were compared.

    ``fps(fp long)`` are distinct. What reaches the driver and goes out again are the nodes of the slices, whose number is bounded.
    """
    if not 0 <= distance <= 64:
        raise ValueError("a distance is a number of bits")
    spark = fps.sparkSession
    n = fps.count()
    rows = max(slice_rows, -(-n // MAX_SLICES))
    slices = materialize(_slices(fps, rows, max(1, -(-n // (4 * rows)))), "slices")
    met = _partners(slices, distance).join(slices.select(F.col("g").alias("other"), "fps"), "other")
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), n // (8 * rows))
    dealt = met.repartition(tasks, "own").sortWithinPartitions("own", F.col("other") != F.col("own"), "other").select("own", "fps")
    return materialize(dealt.mapInArrow(tidy(_meetings(distance)), "u long, v long, visited long, pruned long, compared long"), "met")


def links(fps: DataFrame, distance: int = DISTANCE, slice_rows: int = SLICE) -> DataFrame:
    """``fps(fp long)`` distinct to edges ``(u, v)`` that connect exactly what links within ``distance`` connect."""
    return search(fps, distance, slice_rows).where("u IS NOT NULL").select("u", "v").distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, distance: int = DISTANCE, slice_rows: int = SLICE) -> DataFrame:
    """``(doc_id, fp, component_id)`` for every row.

    Null and wordless texts have fingerprint 0 and link like any other. Repeated rows give repeated rows. An empty
    table gives an empty table. Other columns of ``docs`` are not read, so clashing names do not matter. A null id
    takes part with its text; a component of null ids only has a null id.
    """
    prints = materialize(fingerprints(docs, id_col, text_col, shingle), "prints")
    return prints.join(_classes(prints, distance, slice_rows), "fp").select("doc_id", "fp", "component_id")


def _classes(prints: DataFrame, distance: int, slice_rows: int) -> DataFrame:
    """``(fp, root, component_id)`` of every distinct fingerprint."""
    classes = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("first_doc")), "classes")
    roots = connected_components(links(classes.select("fp"), distance, slice_rows))
    member = classes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", F.coalesce("root", "fp").alias("root"), "first_doc")
    least = member.groupBy("root").agg(F.min("first_doc").alias("component_id"))
    return materialize(member.join(least, "root").select("fp", "root", "component_id"), "components")


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(read_table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def _least_of(docs: DataFrame, rooted: DataFrame) -> DataFrame:
    """One row of each root of ``rooted(doc_id, k, r, root)``: that with the smallest id (null ids last). Whole repeats of it are kept once.

    Texts that stay and are there once pass where they are scanned; only rows that a bitmap of the others' keys points out are dealt out.
    """
    order = F.struct(F.col("doc_id").isNull().alias("n"), "doc_id", "k", "r")
    keep = rooted.groupBy("root").agg(F.min(order).alias("x")).select(F.col("x.k").alias("k"), F.col("x.r").alias("r")).distinct()
    keep = materialize(keep, "keep")
    rows = rooted.groupBy("k", "r").agg(F.count("*").alias("c")).join(keep.withColumn("stays", F.lit(True)), ["k", "r"], "left")
    unsure = bitmap_of(rows.where("c > 1 OR stays IS NULL").select(F.xxhash64("k", "r").alias("a")))
    k, r = _row_key("doc_id", "text")
    keyed = docs.select(F.struct(*docs.columns).alias("row"), k.alias("__k"), r.alias("__r")).withColumn("__a", F.xxhash64("__k", "__r"))
    met = in_bitmap(keyed, unsure, "__a").join(keep.select(F.col("k").alias("__k"), F.col("r").alias("__r")), ["__k", "__r"], "left_semi").dropDuplicates(["__k", "__r"])
    kept = in_bitmap(keyed, unsure, "__a", there=False).select("row").unionByName(met.select("row"))
    return kept.select(*(F.col("row").getField(c).alias(c) for c in docs.columns))


def simhash_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component that op4 finds."""
    prints = materialize(fingerprints(docs), "prints")
    return _least_of(docs, prints.join(_classes(prints, DISTANCE, SLICE), "fp"))


def near_copy_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component, of links as op4 has them and links by sets of five-word shingles."""
    prints = materialize(_signatures(docs), "prints")
    rooted = prints.drop("bands", "m").join(_classes(prints, DISTANCE, SLICE), "fp")
    free_shuffles(spark)
    sets = _set_classes(docs, prints).select(F.col("node").alias("n"), F.col("root").alias("set_root"))
    rooted = materialize(rooted.join(sets, "n", "left").select("doc_id", "k", "r", "root", F.coalesce("set_root", "n").alias("c")), "rooted")
    least = rooted.where("c IS NOT NULL").groupBy("c").agg(F.min("root").alias("u"), F.max("root").alias("top")).where("u <> top").select("c", "u")
    joined = connected_components(rooted.join(least, "c").where("root <> u").select("u", F.col("root").alias("v")).distinct())
    told = rooted.join(joined.select(F.col("node").alias("root"), F.col("root").alias("joined")), "root", "left")
    return _least_of(docs, told.select("doc_id", "k", "r", F.coalesce("joined", "root").alias("root")))
