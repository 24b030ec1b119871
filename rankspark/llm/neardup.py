"""MinHash near-duplicates: SuperMinHash signatures, banding, verification on full sets, union-find grouping.

Each element of a set draws its own random permutation of the signature's places, one place a step, and offers the
value step + fraction there. The ranks of one element are thus all different (correlated), which lowers the variance,
and a document stops as soon as no later step can lower a place. The loop runs over the steps, on all elements of a
batch of documents at once.

A set is a document's distinct word shingles, as 64-bit hashes. Documents with equal sets form a class, found by a
128-bit digest, and only the class's smallest id goes on. Bands of the signature gather candidates; with 32 bands of 4,
a pair at similarity 0.8 shares no band once in 20 million. Then links are confirmed on full sets:

1. in a few bands, each member of a bucket against the bucket's pivot (each bucket has its own order of ids, so a
   document meets many pivots);
2. in all bands the same with other pivots, for members that are not yet in the pivot's component, a few times;
3. every pair of a bucket that is still in two components, so that no link between components is missed. Before sets
   are read, a pair must pass by its sizes and by the differing bits of two parity sketches, which never outnumber the
   differing elements: a test that loses no pair.

Copies collapse beforehand and near copies after the first rounds, so large groups never expand into all pairs.
Components come from star contraction with a union-find in each task; labels never reach the driver. Tables that are
used again are written to the shared folder.

Defined cases: null or empty texts have the empty set, link with nothing and are kept; a text of fewer words than a
shingle is one shingle; repeated rows are copies of each other and share their row's result; rows of one doc_id with
different texts count as one document; a null doc_id links with nothing and is kept; an empty table gives no rows;
other columns are ignored."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

PLACES, BANDS, BITS = 128, 32, 4096
FIRST_BANDS, PIVOT_ROUNDS = 6, 2
#: Members of a bucket that a cell of its pairs takes from each side. A bucket of m members has its rows m / BLOCK times in cells.
BLOCK = 2048
#: A class of more than this share of all rows is joined by broadcast: there are fewer than HEAVY of them.
HEAVY = 10_000
#: Ids that are broadcast at most; more are joined by shuffle.
BROADCAST_ROWS = 500_000
U = np.uint64
GOLD = U(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that scatters them (wraps by design)."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


BLANK = np.zeros(256, dtype=bool)
BLANK[[32, *range(9, 14)]] = True
BYTE = mix(np.arange(256, dtype=U) + GOLD)
PIECE = 1 << 20


def _word_hashes(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Hash and place of each word, from a buffer that ends with a blank; in pieces cut at blanks."""
    hashes, places, at = [], [], 0
    while at < len(raw):
        stop = len(raw)
        if stop - at > PIECE:
            cut = max(raw.rfind(b, at, at + PIECE) for b in (b" ", b"\n"))
            stop = cut + 1 if cut >= at else next((i + 1 for i in range(at + PIECE, len(raw)) if BLANK[raw[i]]), len(raw))
        b = np.frombuffer(raw, dtype=np.uint8, count=stop - at, offset=at)
        blank = BLANK[b]
        edge = np.diff(np.concatenate([[True], blank, [True]]).astype(np.int8))
        start, end = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
        if len(start):
            size = end - start
            own = np.flatnonzero(~blank)
            power = np.cumprod(np.full(int(size.max()), U(0xD6E8FEB86659FD93)))
            inside = np.arange(len(own)) - np.repeat(np.cumsum(size) - size, size)
            sums = np.add.reduceat(BYTE[b[own]] * power[inside], np.cumsum(size) - size)
            hashes.append(mix(sums + size.astype(U) * GOLD))
            places.append(start + at)
        at = stop
    return (np.concatenate(hashes), np.concatenate(places)) if hashes else (np.zeros(0, U), np.zeros(0, np.int64))


def shingle_sets(texts: list[str | None], k: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    raws = [(t or "").encode("utf-8", "surrogatepass").lower() for t in texts]
    ends = np.cumsum([len(r) + 1 for r in raws])
    h, at = _word_hashes(b"".join(r + b" " for r in raws))
    bound = np.concatenate([[0], np.searchsorted(at, ends)])
    run = np.zeros(max(0, len(h) - k + 1), dtype=U)
    for j in range(k):
        run = mix(run * U(0x9FB21C651E98DF25) + h[j : len(h) - k + 1 + j] + GOLD)
    out = []
    for a, z in zip(bound[:-1], bound[1:], strict=True):
        if z - a >= k:
            out.append(np.unique(run[a : z - k + 1]))
        elif z > a:
            short = np.array([U(z - a)])
            for j in range(a, z):
                short = mix(short * U(0xC2B2AE3D27D4EB4F) + h[j])
            out.append(short)
        else:
            out.append(np.zeros(0, U))
    return out


def signatures(sets: list[np.ndarray], places: int = PLACES) -> np.ndarray:
    """(documents, places): the whole part of a value is the step (upper 32 bits), the rest its fraction."""
    chunk = (1 << 23) // places  # elements whose permutations are held at once
    out = np.full((len(sets), places), np.iinfo(np.uint64).max, dtype=U)
    group, size = [], 0
    for i, s in enumerate(sets):
        for at in range(0, len(s), chunk):
            part = s[at : at + chunk]
            if size + len(part) > chunk:
                _offer(out, group)
                group, size = [], 0
            group.append((i, part))
            size += len(part)
    _offer(out, group)
    return out


def _offer(out: np.ndarray, group: list[tuple[int, np.ndarray]]) -> None:
    if not group:
        return
    places = out.shape[1]
    element = np.concatenate([s for _, s in group])
    owner = np.repeat([i for i, _ in group], [len(s) for _, s in group])
    order = np.tile(np.arange(places, dtype=np.uint16), (len(element), 1))
    flat = out.reshape(-1)
    docs = np.unique(owner)
    row = np.arange(len(element))
    for step in range(places):
        r = mix(element + np.array([step + 1], dtype=U) * GOLD)
        draw = (step + (((r & U(0xFFFFFFFF)) * U(places - step)) >> U(32))).astype(np.int64)
        place = order[row, draw]
        order[row, draw] = order[row, step]
        np.minimum.at(flat, owner * places + place, (U(step) << U(32)) | (r >> U(32)))
        going = out[docs].max(axis=1) >= U(step + 1) << U(32)
        if not going.all():
            docs = docs[going]
            if not len(docs):
                return
            wanted = np.zeros(len(out), dtype=bool)
            wanted[docs] = True
            stay = wanted[owner]
            element, owner, row = element[stay], owner[stay], row[stay]


def band_keys(sig: np.ndarray, bands: int = BANDS) -> np.ndarray:
    rows = sig.shape[1] // bands
    key = np.broadcast_to(mix(np.arange(bands, dtype=U) + GOLD), (len(sig), bands)).copy()
    for j in range(rows):
        key = mix(key * U(0x9FB21C651E98DF25) + sig[:, j::rows][:, :bands])
    return key.view(np.int64)


def sketched(docs: DataFrame, k: int) -> DataFrame:
    """doc_id, n_shingles, d1, d2 (digest of the set), bands."""

    def run(batches: Iterator[pa.RecordBatch]):
        for b in common.slices(batches):
            sets = shingle_sets(b.column(1).to_pylist(), k)
            keys = band_keys(signatures(sets))
            digest = np.array([[mix(s).sum(dtype=U), mix(s ^ GOLD).sum(dtype=U)] for s in sets], dtype=U).reshape(-1, 2).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array(digest[:, 0]), pa.array(digest[:, 1]), pa.array(list(keys), pa.list_(pa.int64()))], ["doc_id", "n_shingles", "d1", "d2", "bands"])

    return common.mapped(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, "doc_id long, n_shingles long, d1 long, d2 long, bands array<long>")


def parities(sets: list[np.ndarray]) -> np.ndarray:
    """(documents, BITS / 64): a bit for each cell of a hash of the elements, set where their number is odd.

    Each element of only one of two sets turns one cell, so differing bits never outnumber differing elements."""
    cells = np.stack([np.bincount((mix(s + GOLD) >> U(40)).astype(np.int64) % BITS, minlength=BITS) & 1 for s in sets])
    return np.packbits(cells.astype(np.uint8), axis=1).view(np.int64)


def full_sets(docs: DataFrame, k: int) -> DataFrame:
    """id, set, bands, bits, brief: for candidates only. brief is bits folded to a quarter."""

    def run(batches: Iterator[pa.RecordBatch]):
        for b in common.slices(batches):
            sets = shingle_sets(b.column(1).to_pylist(), k)
            bits = parities(sets)
            lists = lambda m: pa.array(list(m), pa.list_(pa.int64()))
            brief = np.bitwise_xor.reduce(bits.reshape(len(bits), 4, -1), axis=1)
            yield pa.RecordBatch.from_arrays([b.column(0), lists(s.view(np.int64) for s in sets), lists(band_keys(signatures(sets))), lists(bits), lists(brief)], ["id", "set", "bands", "bits", "brief"])

    return common.mapped(docs.select(F.col("doc_id").cast("long").alias("id"), "text"), run, "id long, set array<long>, bands array<long>, bits array<long>, brief array<long>")


def _possible(percent: int):
    """Whether two documents (na, fa, ta: size, brief and bits; nb, fb, tb) may have the similarity: it needs sizes near each
    other and at most (100 - percent) / (100 + percent) of both sizes in differing elements, hence in differing bits. No pair is lost."""
    differ = lambda x, y: F.bit_count(x.bitwiseXOR(y))
    few = differ(F.get("fa", F.lit(0)), F.get("fb", F.lit(0)))
    for i in range(1, BITS // 256):
        few = few + differ(F.get("fa", F.lit(i)), F.get("fb", F.lit(i)))
    every = F.aggregate(F.zip_with("ta", "tb", differ), F.lit(0), lambda x, y: x + y)
    most = (100 - percent) * (F.col("na") + F.col("nb"))
    return (100 * F.least("na", "nb") >= percent * F.greatest("na", "nb")) & ((100 + percent) * few <= most) & ((100 + percent) * every <= most)


def _own(sets: DataFrame, side: str, *more) -> DataFrame:
    return sets.select(*more, F.size("set").alias(f"n{side}"), F.col("brief").alias(f"f{side}"), F.col("bits").alias(f"t{side}"))


def _near(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs that sizes and bits allow, before any set is read."""
    return pairs.join(_own(sets, "a", F.col("id").alias("u")), "u").join(_own(sets, "b", F.col("id").alias("v")), "v").where(_possible(percent)).select("u", "v")


def _crossing(rest: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(u, v): pairs of a bucket from two components that sizes and bits allow, each in the first band that they share only.
    All tests are part of the join, so other pairs are never rows. A bucket of more than BLOCK members is dealt to blocks, and
    each pair of blocks is a cell of its own, so no task holds more than two blocks of a bucket."""
    sizes = rest.groupBy("band", "key").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks"))
    large = sizes.where("blocks > 1")  # at most rows / BLOCK of them
    a = rest.join(large, ["band", "key"], "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    a = a.withColumn("block", F.pmod(F.xxhash64("rep", "band"), F.col("blocks")).cast("int"))
    cell = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda y: F.least("block", y) * F.col("blocks") + F.greatest("block", y))
    a = a.withColumn("cell", F.explode(cell)).withColumn("inside", F.col("cell") == F.col("block") * (F.col("blocks") + 1))
    a = a.join(_own(sets, "a", F.col("id").alias("rep"), F.col("bands").alias("ba")), "rep")
    a = a.select("band", "key", "cell", F.col("block").alias("xa"), "inside", F.col("rep").alias("ra"), F.col("c").alias("ca"), "na", "ba", "fa", "ta")
    b = a.toDF("band_b", "key_b", "cell_b", "xb", "inside_b", "rb", "cb", "nb", "bb", "fb", "tb")
    first = F.array_position(F.zip_with("ba", "bb", lambda x, y: x == y), True) == F.col("band") + 1
    same = (F.col("band") == F.col("band_b")) & (F.col("key") == F.col("key_b")) & (F.col("cell") == F.col("cell_b"))
    met = a.join(b, same & (F.col("inside") | (F.col("xa") != F.col("xb"))) & (F.col("ca") < F.col("cb")) & _possible(percent) & first)
    return met.select(*_ordered("ra", "rb"))


# ---- components ------------------------------------------------------------------------------------------------


def _forest(edges: DataFrame) -> DataFrame:
    """(u, v) with u > v: the stars that a union-find over each task's own edges leaves. A task gives its stars out and
    starts anew after 200,000 edges, so its memory is bounded."""

    def run(batches: Iterator[pa.RecordBatch]):
        root: dict[int, int] = {}

        def find(x: int) -> int:
            while (up := root.get(x, x)) != x:
                root[x] = x = root.get(up, up)
            return x

        def stars():
            u = [x for x in root if find(x) != x]
            return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array([find(x) for x in u], pa.int64())], ["u", "v"])

        for b in batches:
            for x, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                a, z = sorted((find(x), find(y)))
                root[z] = root.setdefault(a, a)
            if len(root) > 200_000:
                yield stars()
                root.clear()
        yield stars()

    return edges.select("u", "v").mapInArrow(run, "u long, v long")


def components(edges: DataFrame) -> DataFrame:
    """(v, component) for every id that occurs in edges (u, v); the component is its smallest id.

    Large and small stars in turn: each id's neighbours are tied to the smallest of them, until nothing changes."""
    now = common.stored(_forest(edges.where("u != v")).distinct(), "stars")
    before = None
    while True:
        size = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if not size[0] or size == before:
            return now.select(F.col("u").alias("v"), F.col("v").alias("component")).unionByName(now.select("v", F.col("v").alias("component")).distinct())
        before = size
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").unionByName(low.select("u", F.col("m").alias("v"))).distinct()
        now = common.stored(small, "stars")


# ---- linking ---------------------------------------------------------------------------------------------------


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (u, v) whose sets have 100 * intersection >= percent * union."""
    a, b = sets.select(F.col("id").alias("u"), F.col("set").alias("su")), sets.select(F.col("id").alias("v"), F.col("set").alias("sv"))
    both = F.size(F.array_intersect("su", "sv")).cast("long")
    return pairs.join(a, "u").join(b, "v").where(100 * both >= percent * (F.size("su") + F.size("sv") - both)).select("u", "v")


def _labelled(df: DataFrame, labels: DataFrame, column: str, name: str) -> DataFrame:
    known = labels.select(F.col("v").alias(column), F.col("component").alias(name))
    return df.join(known, column, "left").withColumn(name, F.coalesce(name, column))


def _ordered(a: str, b: str) -> list:
    return [F.greatest(a, b).alias("u"), F.least(a, b).alias("v")]


def group(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, kept: one row for each row of docs."""
    sketch = common.stored(sketched(docs, k), "sketch")
    real = sketch.where("n_shingles > 0 and doc_id is not null")
    classes = real.groupBy("d1", "d2").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"))
    heads = real.join(classes.select(F.col("rep").alias("doc_id"), "d1", "d2"), ["doc_id", "d1", "d2"], "left_semi")
    spread = heads.select(F.col("doc_id").alias("rep"), F.posexplode("bands").alias("band", "key"))
    shared = spread.groupBy("band", "key").agg(F.min("rep").alias("a"), F.max("rep").alias("z")).where("a < z").select("band", "key")
    buckets = common.stored(spread.join(shared, ["band", "key"]), "buckets")
    ids = buckets.select("rep").distinct()
    ids = F.broadcast(ids) if ids.count() <= BROADCAST_ROWS else ids
    sets = common.stored(full_sets(docs.join(ids, docs["doc_id"] == ids["rep"], "left_semi"), k).dropDuplicates(["id"]), "sets")
    tried = links = labels = None

    def confirm(pairs: DataFrame, sifted: bool = False) -> bool:
        """Verify pairs that no round has tried, and bring the components up to date; whether links were found."""
        nonlocal tried, links, labels
        new = common.stored(pairs if tried is None else pairs.join(tried, ["u", "v"], "left_anti"), "pairs")
        fresh = common.stored(_verified(new if sifted else _near(new, sets, percent), sets, percent), "links")
        tried = new if tried is None else tried.unionByName(new)
        if found := not fresh.isEmpty():
            links = fresh if links is None else links.unionByName(fresh)
            labels = components(links)
        return found

    named = lambda df, column, name: df.withColumn(name, F.col(column)) if labels is None else _labelled(df, labels, column, name)
    open_buckets = lambda df: df.join(df.groupBy("band", "key").agg(F.min("c").alias("a"), F.max("c").alias("z")).where("a < z").select("band", "key"), ["band", "key"])
    for turn in range(PIVOT_ROUNDS):
        part = buckets.where(F.col("band") < FIRST_BANDS) if turn == 0 else buckets
        part = open_buckets(named(part.select("band", "key", "rep"), "rep", "c"))
        part = part.withColumn("p", F.col("rep").bitwiseXOR(F.shiftrightunsigned(F.xxhash64(F.lit(turn), "band", "key"), 1)))
        low = part.groupBy("band", "key").agg(F.min("p").alias("low"))
        tied = part.join(low, ["band", "key"]).select("rep", "c", F.col("low").bitwiseXOR(F.col("rep").bitwiseXOR(F.col("p"))).alias("pivot")).distinct()
        if not confirm(named(tied, "pivot", "cp").where("c != cp").select(*_ordered("rep", "pivot")).distinct()) and turn:
            break
    rest = common.stored(open_buckets(named(buckets.select("band", "key", "rep"), "rep", "c")), "rest")
    confirm(_crossing(rest, sets, percent), sifted=True)
    if labels is None:
        labels = components(tried.limit(0))

    final = _labelled(classes, labels, "rep", "component_id").select("d1", "d2", F.col("component_id").alias("found"), "copies")
    # empty sets join with nothing; classes that hold a large share of the rows travel to them, the others meet theirs by shuffle
    rows = sketch.select("doc_id", "n_shingles", "d1", "d2")
    least = real.count() // HEAVY
    heavy = final.where((F.col("copies") > least) & (F.col("copies") > 1))
    apart = rows.where("not (n_shingles > 0 and doc_id is not null)").withColumn("found", F.col("doc_id"))
    own = rows.where("n_shingles > 0 and doc_id is not null").join(F.broadcast(heavy.select("d1", "d2", F.col("found").alias("held"))), ["d1", "d2"], "left")
    own = common.stored(own, "classes")
    others = own.where("held is null").drop("held").join(final.select("d1", "d2", "found"), ["d1", "d2"])
    out = own.where("held is not null").withColumnRenamed("held", "found").unionByName(others).unionByName(apart)
    return out.select("doc_id", "n_shingles", F.col("found").alias("component_id"), (F.col("doc_id").eqNullSafe(F.col("found"))).alias("kept"))


def deduplicated(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """The rows of docs without the near copies: of each group the document with the smallest id stays, once."""
    groups = common.stored(group(docs, k, percent), "groups")
    gone = groups.where("not kept").select("doc_id").distinct()
    gone = F.broadcast(gone) if gone.count() <= BROADCAST_ROWS else gone
    left = docs.join(gone, "doc_id", "left_anti")
    repeated = groups.where("doc_id is not null").groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    return left if repeated.isEmpty() else left.dropDuplicates(["doc_id"])


#: The grouping by 2-word shingles in plain SQL, for small tables.
SQL = r"""
WITH RECURSIVE d AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, array_to_string(w[i + 1:i + least(2, len(w))], ' ') AS g FROM (SELECT doc_id, w, unnest(range(0, greatest(1, len(w) - 1))) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
e AS (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * p.k >= 80 * (a.n + b.n - p.k)),
l AS (SELECT x, y FROM e UNION SELECT y, x FROM e),
r AS (SELECT doc_id, doc_id AS c FROM d UNION SELECT l.y, r.c FROM r JOIN l ON l.x = r.doc_id)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, c.c AS component_id, d.doc_id = c.c AS kept
FROM d LEFT JOIN n ON n.doc_id = d.doc_id JOIN (SELECT doc_id, min(c) AS c FROM r GROUP BY doc_id) c ON c.doc_id = d.doc_id"""
