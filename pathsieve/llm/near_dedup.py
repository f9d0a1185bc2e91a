"""Near-duplicate documents by circulant MinHash, banding and exact Jaccard verification."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.llm import kernels as K
from pathsieve.loop import cut, scratch

BANDS, ROWS = 34, 6
#: Standard deviations below the mean of a pair at the threshold, at which signature bits reject a candidate.
SLACK = 5.0
#: Set elements in a block where blocks of sets are compared.
BLOCK_ELEMENTS = 16_384
#: Rows in a block where signatures of one bucket are compared.
BLOCK_ROWS = 512
_BITS = ("s0", "s1", "s2", "s3")
#: What tells a row apart: whether it has no doc_id (such rows come last), its doc_id, and two hashes of its text.
_ROW = ("none", "key", "t1", "t2")
_U32 = np.uint32


def _bijection(x: np.ndarray) -> np.ndarray:
    """The second permutation: of the universe of 2**32 positions, in place."""
    x ^= x >> _U32(16)
    x *= _U32(0x7FEB352D)
    x ^= x >> _U32(15)
    x *= _U32(0x846CA68B)
    x ^= x >> _U32(16)
    return x


def circulant_signatures(sets: np.ndarray, rows: np.ndarray, size: int) -> np.ndarray:
    """MinHash signatures, shape (rows, size), of non-empty sets of 64-bit hashes.

    A first permutation scatters an element to a position; coordinate k is the minimum of a
    second permutation, read at that position moved round by k. Two permutations thus give
    all coordinates.
    """
    position = (K.mix64(sets.copy()) >> K.U64(32)).astype(_U32)
    out = np.empty((len(rows) - 1, size), _U32)
    for k in range(size):
        out[:, k] = np.minimum.reduceat(_bijection(position + _U32(k)), rows[:-1])
    return out


def band_keys(signatures: np.ndarray, bands: int, per_band: int) -> np.ndarray:
    """One 64-bit key for each band of a signature."""
    keys = np.zeros((len(signatures), bands), K.U64)
    for j in range(per_band):
        keys *= K.U64(0x9FB21C651E98DF25)
        keys += signatures[:, j : bands * per_band : per_band].astype(K.U64) + K.U64(1)
    return K.mix64(keys)


def signature_bits(signatures: np.ndarray) -> np.ndarray:
    """The lowest bits of the first 256 coordinates as four 64-bit words for each row."""
    low = np.zeros((len(signatures), 256), np.uint8)
    low[:, : signatures.shape[1]] = signatures[:, :256] & _U32(1)
    return np.packbits(low, axis=1, bitorder="little").view("<u8")


def most_unequal_bits(size: int, percent: int) -> int:
    """Bits that may differ: a bit agrees with probability (1 + similarity) / 2."""
    size, agree = min(size, 256), (100 + percent) / 200
    return math.ceil(size * (1 - agree) + SLACK * math.sqrt(size * agree * (1 - agree)))


def _sets(column: pa.Array, k: int):
    """For each chunk of rows: its range, and the rows' distinct shingle hashes."""
    data, offsets = K.flat(column)
    for i, j in K.chunks(offsets):
        b = K.LOWER[data[offsets[i] : offsets[j]]]
        starts, ends, rows = K.words(b, offsets[i : j + 1] - offsets[i], K.NOT_SPACE)
        yield i, j, *K.distinct(*K.shingles(K.spans_hash(b, starts, ends), rows, k, whole=True))


def _signed(batches, k: int, bands: int, per_band: int):
    for batch in batches:
        parts = []
        for i, j, values, rows in _sets(batch.column("text"), k):
            n = np.diff(rows)
            full = np.flatnonzero(n)
            keys = np.zeros((j - i, 2), K.U64)
            marks = np.zeros((0, bands), K.U64)
            bits = np.zeros((j - i, 4), K.U64)
            if len(full):
                at = np.append(rows[:-1][full], rows[-1])
                keys[full, 0] = np.add.reduceat(K.mix64(values.copy()), at[:-1])
                keys[full, 1] = np.add.reduceat(K.mix64(values * K.U64(0xA0761D6478BD642F)), at[:-1])
                signatures = circulant_signatures(values, at, bands * per_band)
                marks, bits[full] = band_keys(signatures, bands, per_band), signature_bits(signatures)
            at = np.concatenate([[0], np.cumsum(np.where(n > 0, bands, 0))])
            parts.append(pa.RecordBatch.from_arrays([
                *(batch.column(c).slice(i, j - i) for c in ("doc_id", *_ROW)), pa.array(n, pa.int64()),
                pa.array(keys[:, 0].view(np.int64)), pa.array(keys[:, 1].view(np.int64)),
                *(pa.array(np.ascontiguousarray(bits[:, c]).view(np.int64)) for c in range(4)),
                K.lists(marks.reshape(-1).view(np.int64), at, pa.int64()),
            ], names=["doc_id", *_ROW, "n_shingles", "k1", "k2", *_BITS, "bands"]))
        yield from parts


def _full_sets(batches, k: int):
    for batch in batches:
        for i, j, values, rows in _sets(batch.column("text"), k):
            yield pa.RecordBatch.from_arrays([
                batch.column("id").slice(i, j - i), K.lists(values.view(np.int64), rows, pa.int64()),
            ], names=["id", "elements"])


def components(edges: DataFrame) -> DataFrame:
    """(id, component) for every id in ``edges`` (a, b): the smallest id that it reaches.

    Each round takes the least label among the neighbours and then the label of the label,
    so the number of rounds grows with the logarithm of a component's width.
    """
    both = cut(edges.select("a", "b").union(edges.select("b", "a")).where("a <> b").distinct(), "links")
    labels = cut(both.groupBy(F.col("a").alias("id")).agg(F.least(F.min("b"), F.first("a")).alias("component")), "labels")
    while True:
        low = both.join(labels, both.b == labels.id).groupBy("a").agg(F.min("component").alias("low"))
        near = labels.join(low, labels.id == low.a, "left").select("id", F.col("component").alias("was"), F.least("component", F.coalesce("low", "component")).alias("near"))
        near = cut(near, "near")
        up = near.select(F.col("id").alias("up"), F.col("near").alias("above"))
        step = near.join(up, near.near == up.up, "left").select("id", "was", F.least("near", F.coalesce("above", "near")).alias("component"))
        step = cut(step, "labels")
        if step.where("component <> was").isEmpty():
            return step.select("id", "component")
        labels = step.select("id", "component")


def _close(percent: int, unequal: int) -> str:
    """Condition on the sizes and signature bits of a pair (na, a0.. and nb, b0..)."""
    apart = " + ".join(f"bit_count(a{c} ^ b{c})" for c in range(4))
    return f"100 * least(na, nb) >= {percent} * greatest(na, nb) AND {apart} <= {unequal}"


def _side(info: DataFrame, side: str) -> DataFrame:
    """Size and signature bits under the names of one side of a pair."""
    return info.select(F.col("id").alias(side), F.col("n").alias(f"n{side}"), *[F.col(x).alias(f"{side}{c}") for c, x in enumerate(_BITS)])


def _keys(docs: DataFrame) -> list[Column]:
    """The columns of ``_ROW``, none of them ever null."""
    id_type = dict(docs.dtypes)["doc_id"]
    nothing = F.lit("" if id_type == "string" else 0).cast(id_type)
    key = [docs["doc_id"].isNull(), F.coalesce(docs["doc_id"], nothing), F.xxhash64(docs["text"]), F.hash(docs["text"])]
    return [c.alias(n) for c, n in zip(key, _ROW, strict=True)]


def _node_sets(nodes: DataFrame, classes: DataFrame, texts: DataFrame, shingle: int) -> DataFrame:
    """(id, elements): the full sets of classes, read again from the text of one row of each."""
    wanted = classes.join(nodes.select("id").distinct(), "id", "left_semi").select("id", "rep.*")
    rows = texts.join(wanted.hint("merge"), list(_ROW)).dropDuplicates(list(_ROW)).select("id", "text")
    return cut(rows.mapInArrow(lambda it: _full_sets(it, shingle), "id long, elements array<long>"), "sets")


def _linked(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets are similar enough."""
    near = pairs.join(sets.select(F.col("id").alias("a"), F.col("elements").alias("ea")), "a")
    both = near.join(sets.select(F.col("id").alias("b"), F.col("elements").alias("eb")), "b")
    counted = both.select("a", "b", F.size("ea").alias("na"), F.size("eb").alias("nb"), F.size(F.array_intersect("ea", "eb")).alias("same"))
    return cut(counted.where(f"100 * same >= {percent} * (na + nb - same)").select("a", "b"), "edges")


def _ends(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.col("a").alias("id")).union(pairs.select("b"))


def _block_pairs(batches, percent: int):
    """Links between two blocks of sets: all intersections of one set with a block come from one look-up."""
    for batch in batches:
        a, b = [], []
        columns = [batch.column(c).to_pylist() for c in ("outer", "inner")]
        for outer, inner in zip(*columns, strict=True):
            sizes = np.array([len(x["elements"]) for x in inner])
            values = np.concatenate([np.array(x["elements"], np.int64) for x in inner])
            owner = np.repeat(np.arange(len(inner)), sizes)
            order = np.argsort(values, kind="stable")
            values, owner = values[order], owner[order]
            for x in outer:
                own = np.array(x["elements"], np.int64)
                lo, hi = np.searchsorted(values, own, "left"), np.searchsorted(values, own, "right")
                same = np.bincount(owner[K.ragged(lo, hi - lo)], minlength=len(inner))
                for y in np.flatnonzero(100 * same >= percent * (len(own) + sizes - same)):
                    a.append(x["id"])
                    b.append(inner[y]["id"])
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])


def _block_links(inner: DataFrame, outer: DataFrame, sets: DataFrame, percent: int, block: int = BLOCK_ELEMENTS) -> DataFrame:
    """Links between the sets of ``outer`` and ``inner`` (id, n, main) with the same main.

    Each side of a main is dealt into blocks of about ``block`` elements by a hash of id; every block of one side meets every block of
    the other in a row of its own, so neither a hot main nor its pairs ever meet in one task.
    """
    shares = lambda df, name: df.groupBy("main").agg(F.ceil(F.sum("n") / block).alias(name))
    plan = cut(shares(inner, "rows").join(shares(outer, "columns"), "main"), "blocks")
    dealt = lambda df, count, to: df.join(plan, "main").select("id", "main", "rows", F.pmod(F.xxhash64("id"), F.col(count)).alias(to)).join(sets, "id")
    packed = F.collect_list(F.struct("id", "elements"))
    in_blocks = dealt(inner, "rows", "row").groupBy("main", "row").agg(packed.alias("inner"))
    out_blocks = dealt(outer, "columns", "column").groupBy("main", "column").agg(packed.alias("outer"), F.first("rows").alias("rows"))
    met = out_blocks.withColumn("row", F.explode(F.sequence(F.lit(0).cast("long"), F.col("rows") - 1))).join(in_blocks, ["main", "row"])
    return cut(met.select("outer", "inner").mapInArrow(lambda it: _block_pairs(it, percent), "a long, b long"), "edges")


def _bucket_pairs(rows: DataFrame, info: DataFrame, close: str, block: int = BLOCK_ROWS) -> DataFrame:
    """Pairs (a, b) of rows (band, key, id, component) of one bucket in different components that may be similar.

    A bucket is dealt into blocks of about ``block`` rows by a hash of id; each two blocks meet under a key of their own, so no
    bucket meets itself in one task.
    """
    bucket = ["band", "key"]
    plan = cut(rows.groupBy(*bucket).agg(F.ceil(F.count("*") / block).alias("blocks"), F.count_distinct("component").alias("parts")).where("parts > 1").drop("parts"), "blocks")
    dealt = rows.join(plan, bucket).withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")))
    dealt = cut(dealt.join(info, "id"), "dealt")
    side = lambda name, own: dealt.select(*bucket, F.col("id").alias(name), F.col("component").alias(own), "block", "blocks", F.col("n").alias(f"n{name}"), *[F.col(x).alias(f"{name}{c}") for c, x in enumerate(_BITS)])
    last = F.col("blocks") - 1
    left = side("a", "own").withColumn("upper", F.explode(F.sequence(F.col("block"), last))).withColumnRenamed("block", "lower").drop("blocks")
    right = side("b", "other").withColumn("lower", F.explode(F.sequence(F.lit(0).cast("long"), F.col("block")))).withColumnRenamed("block", "upper").drop("blocks")
    met = left.join(right, [*bucket, "lower", "upper"]).where(f"own <> other AND (lower < upper OR a < b) AND {close}")
    return cut(met.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "pairs")


def _grouped(docs: DataFrame, shingle: int, percent: int, bands: int, per_band: int) -> DataFrame:
    """For each row: doc_id, the columns of ``_ROW``, n_shingles, component_id, and whether it is the first row of its component."""
    texts = docs.select("doc_id", "text", *_keys(docs))
    id_type = dict(texts.dtypes)["doc_id"]
    with scratch(docs.sparkSession) as held:
        bits = ", ".join(f"{x} long" for x in _BITS)
        kind = f"doc_id {id_type}, none boolean, key {id_type}, t1 long, t2 int, n_shingles long, k1 long, k2 long, {bits}, bands array<long>"
        base = held.keep(cut(texts.mapInArrow(lambda it: _signed(it, shingle, bands, per_band), kind), "signed"))
        same = ["k1", "k2", "n_shingles"]
        classes = base.where("n_shingles > 0").groupBy(*same).agg(F.min(F.struct(*_ROW)).alias("rep"), *[F.first(x).alias(x) for x in (*_BITS, "bands")])
        classes = cut(classes.withColumn("id", F.monotonically_increasing_id()), "classes")
        leaders = classes.select("id", F.col("n_shingles").alias("n"), *_BITS, "bands")
        exploded = leaders.select("id", F.posexplode("bands").alias("band", "key"))
        bucket = ["band", "key"]
        pivots = cut(exploded.groupBy(*bucket).agg(F.min("id").alias("a"), F.count("*").alias("m")).where("m > 1").drop("m"), "pivots")
        members = cut(exploded.join(pivots, bucket).where("id <> a"), "members")
        in_buckets = members.select("id").union(members.select("a")).distinct()
        info = cut(leaders.drop("bands").join(in_buckets, "id", "left_semi"), "info")
        close = _close(percent, most_unequal_bits(bands * per_band, percent))
        star = members.select("a", F.col("id").alias("b")).distinct().join(_side(info, "b"), "b").join(_side(info, "a"), "a").where(close)
        star = cut(star.select("a", "b"), "pairs")
        edges = _linked(star, _node_sets(_ends(star), classes, texts, shingle), percent)
        labels = components(edges)
        marked = members.select(*bucket, "id").join(labels, "id", "left").withColumn("component", F.coalesce("component", "id"))
        shares = marked.groupBy(*bucket, "component").agg(F.count("*").alias("c"))
        tops = shares.groupBy(*bucket).agg(F.min(F.struct((-F.col("c")).alias("c"), "component")).alias("x"), F.count("*").alias("parts")).where("parts > 1")
        main = cut(tops.select(*bucket, F.col("x.component").alias("main")), "main")
        rest = cut(marked.join(main, bucket), "rest")
        sized = rest.join(info.select("id", "n"), "id")
        inner = sized.where("component = main").select("id", "n", "main").distinct()
        outer = sized.where("component <> main").select("id", "n", "main").distinct()
        sets = _node_sets(rest.select("id"), classes, texts, shingle)
        across = _block_links(inner, outer, sets, percent)
        if not across.isEmpty():
            edges = edges.union(across)
            labels = components(edges)
        now = lambda name, to: labels.select(F.col("id").alias(name), F.col("component").alias(to))
        placed = outer.join(now("id", "own"), "id", "left").join(now("main", "top"), "main", "left")
        placed = cut(placed.select("id", "n", "main", F.coalesce("own", "id").alias("own"), F.coalesce("top", "main").alias("top")), "placed")
        joined, still = (placed.where(c).select("id", "n", "main") for c in ("own = top", "own <> top"))
        late = _block_links(joined, still, sets, percent)
        if not late.isEmpty():
            edges = edges.union(late)
        apart = rest.where("component <> main").drop("component").join(now("id", "own"), "id", "left").join(now("main", "top"), "main", "left")
        apart = apart.select(*bucket, "id", F.coalesce("own", "id").alias("component"), F.coalesce("top", "main").alias("top")).where("component <> top").drop("top")
        more = _linked(_bucket_pairs(cut(apart, "apart"), info, close), sets, percent)
        if not more.isEmpty() or not late.isEmpty():
            labels = components(edges.union(more))
        joined = classes.join(labels, "id", "left").select(*same, "rep", F.coalesce("component", "id").alias("component"))
        least = joined.groupBy("component").agg(F.min("rep").alias("first"))
        groups = held.keep(cut(joined.join(least, "component").select(*same, "first"), "groups"))
    rows = base.select("doc_id", *_ROW, *same).join(groups, same, "left")
    own = F.when(F.col("first.none"), F.lit(None)).otherwise(F.col("first.key"))
    component = F.when(F.col("n_shingles") > 0, own).otherwise(F.col("doc_id"))
    return rows.select("doc_id", *_ROW, "n_shingles", component.alias("component_id"), (F.struct(*_ROW) == F.col("first")).alias("is_first"))


def near_duplicates(docs: DataFrame, shingle: int = 4, percent: int = 80, bands: int = BANDS, per_band: int = ROWS) -> DataFrame:
    """Components of documents with Jaccard similarity of at least ``percent``/100.

    Takes ``doc_id`` and ``text``; returns, for each row, doc_id, n_shingles, component_id
    (smallest doc_id that links reach) and kept (doc_id = component_id). Other columns are
    not read. A document's set holds its distinct shingles of ASCII-lower-cased words; with fewer
    words, the whole sequence is the one element. Null and wordless texts have an empty set
    and are linked with nothing. Rows that repeat a doc_id each give a row and are compared by their own texts; a row without
    doc_id takes part like any other, and its component's id is null only where no member has one.

    Rows whose sets agree in size and in two independent 64-bit sums over all elements become one class by an
    aggregate; classes, numbered as they are written, are what is banded, so neither copies nor
    null or repeated ids matter from there on. In each bucket, the smallest class is compared with all others. Where a bucket still
    holds several components, the members outside its most frequent one are compared with those of that component, block
    of full sets against block of full sets; those that a link has joined to it by then are compared with those still apart in the
    same way, and the latter meet each other, block of signatures against block of signatures. So no pair that shares a bucket and might join two components is given up, and no step puts a bucket into one task. Pairs whose sizes
    or signature bits rule the similarity out are dropped before their full sets are compared. At a similarity of 0.8, a pair shares no
    bucket with a probability of (1 - 0.8**per_band)**bands, 3e-5 by default, and its bits rule it out
    with less than 1e-6.
    """
    found = _grouped(docs, shingle, percent, bands, per_band)
    return found.select("doc_id", "n_shingles", "component_id").withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def without_near_duplicates(docs: DataFrame, shingle: int = 5, percent: int = 80) -> DataFrame:
    """One row of each component of ``docs``, the first by doc_id (rows without one come last); all columns stay.

    Shingles have five words here, as in all stages without a contract of their own. Null and wordless texts all stay. Rows are told
    apart by doc_id and text, so a text that shares its doc_id with a copy of another text stays; of rows equal in both, one stays.
    """
    found = _grouped(docs, shingle, percent, BANDS, ROWS).where("n_shingles > 0")
    with scratch(docs.sparkSession) as held:
        decided = found.groupBy(*_ROW).agg(F.first("is_first").alias("is_first"), F.count("*").alias("c")).where("NOT is_first OR c > 1")
        decided = held.keep(cut(decided, "decided"))
    carried = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), *_keys(docs))
    once = carried.join(decided.select(*_ROW), list(_ROW), "left_anti").select("row.*")
    again = decided.where("is_first")
    if again.isEmpty():
        return once
    repeated = carried.join(again.select(*_ROW), list(_ROW), "left_semi").dropDuplicates(list(_ROW))
    return once.unionByName(repeated.select("row.*"))

