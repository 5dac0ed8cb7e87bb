"""Near-duplicate documents by SetSketch registers.

A register holds the exponent of the least of exponentially distributed values: element by element the
k-th value falls into the k-th of m intervals (truncated exponentials, SetSketch in its second form), so
sets of any size cost about m log m + n steps, and registers of a union are the larger of both. Equal
register bands propose pairs, a joint likelihood over registers larger, smaller and equal rejects most,
full sets decide. Equal sets are one node; only distinct sets are compared.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators.cluster import components
from .common import free_name, settle

M, BAND, BASE, RATE, TOP = 128, 4, 1.001, 20.0, 65535
REMEMBER = 300_000  # words whose hashes a task keeps
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_GOLDEN = np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    """The splitmix64 finisher."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class _WordHashes(defaultdict):
    def __missing__(self, word: bytes) -> int:
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


def shingle_sets(texts: list[bytes], k: int, hashes: dict | None = None) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of each text's k-word shingles; fewer words are one shingle; none, none."""
    hashes = _WordHashes() if hashes is None else hashes
    lists = [t.translate(_FOLD).split() for t in texts]
    lengths = np.array([len(x) for x in lists], "i8")
    words = np.array([hashes[w] for x in lists for w in x], "u8")
    ends = np.cumsum(lengths)
    whole = np.zeros(max(len(words) - k + 1, 0), "u8")
    for i in range(k):
        whole = mix(whole + words[i : i + len(whole)] + _GOLDEN)
    out = []
    for n, end in zip(lengths.tolist(), ends.tolist(), strict=True):
        if n >= k:
            out.append(np.unique(whole[end - n : end - k + 1]))
        elif n:
            h = np.full(1, n, "u8")
            for w in words[end - n : end]:
                h = mix(h + w + _GOLDEN)
            out.append(h)
        else:
            out.append(words[:0])
    return out


def _intervals() -> np.ndarray:
    k = np.arange(M)
    return np.append(np.log1p(k / (M - k)) / RATE, np.inf)


def sketch(sets: list[np.ndarray]) -> np.ndarray:
    """Registers (len(sets), M) as unsigned 16-bit exponents; 0 where a set is empty."""
    sizes = np.array([len(s) for s in sets], "i8")
    least = np.full(len(sets) * M, np.inf)
    element = np.concatenate(sets) if sets else np.empty(0, "u8")
    owner = np.repeat(np.arange(len(sets)), sizes)
    place = mix(element + np.uint64(1))
    step = (place >> np.uint64(40)).astype("i8") * 2 + 1  # odd, so all M places are met
    place = (place & np.uint64(M - 1)).astype("i8")
    edges = _intervals()
    for k in range(M):
        low, high = edges[k], edges[k + 1]
        u = (mix(element + np.uint64((k + 2) * int(_GOLDEN) % 2**64)) >> np.uint64(11)).astype("f8") * 2.0**-53
        x = low - np.log1p(-u * -np.expm1(-RATE * (high - low))) / RATE
        np.minimum.at(least, owner * M + ((place + k * step) & (M - 1)), x)
        live = high < least.reshape(-1, M).max(1)[owner]  # later values cannot be smaller than high
        if not live.all():
            element, owner, place, step = element[live], owner[live], place[live], step[live]
        if not len(element):
            break
    with np.errstate(divide="ignore"):
        exponents = np.floor(1 - np.log(least) / np.log(BASE))
    return np.clip(exponents, 0, TOP).astype("u2").reshape(-1, M)


def merge(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Registers of the union."""
    return np.maximum(a, b)


def bands_of(registers: Column) -> Column:
    """An array of M // BAND keys, each of a band's number and its BAND register values."""
    return F.transform(F.sequence(F.lit(0), F.lit(M // BAND - 1)), lambda i: F.xxhash64(i, F.substring(registers, i * (2 * BAND) + 1, F.lit(2 * BAND))))


def likely_jaccard(a: np.ndarray, b: np.ndarray, n_a: np.ndarray, n_b: np.ndarray, steps: int = 40) -> np.ndarray:
    """Similarity of greatest joint likelihood, set sizes being known, from how many registers are larger
    in a, larger in b, and equal. The likelihood is concave; its peak is enclosed by thirds."""
    more, less = (a > b).sum(1), (a < b).sum(1)
    same = a.shape[1] - more - less
    u, v = n_a / (n_a + n_b), n_b / (n_a + n_b)
    p = lambda x: -np.log1p(-np.clip(x, 0, 1) * (BASE - 1) / BASE) / np.log(BASE)

    def value(j: np.ndarray) -> np.ndarray:
        up, down = p(u - v * j), p(v - u * j)
        log = lambda c, x: np.where(c > 0, c * np.log(np.maximum(x, 1e-300)), 0.0)
        return log(more, up) + log(less, down) + log(same, 1 - up - down)

    low, high = np.zeros(len(a)), np.minimum(u / v, v / u)
    for _ in range(steps):
        third = (high - low) / 3
        left = value(low + third) < value(high - third)
        low, high = np.where(left, low + third, low), np.where(left, high, high - third)
    return (low + high) / 2


def _chunks(texts: list[bytes], limit: int = 1_000_000) -> Iterator[tuple[int, int]]:
    start = held = 0
    for i, t in enumerate(texts):
        if held and held + len(t) > limit:
            yield start, i
            start, held = i, 0
        held += len(t)
    if start < len(texts):
        yield start, len(texts)


def sketches(docs: DataFrame, k: int, id_col: str, text_col: str) -> DataFrame:
    """doc_id, n_shingles, digest of the set (null if empty) and registers."""
    schema = f"doc_id {docs.schema[id_col].dataType.simpleString()}, n_shingles long, digest binary, registers binary"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = _WordHashes()
        for batch in batches:
            texts = [t or b"" for t in batch.column(1).cast(pa.binary()).to_pylist()]
            for a, b in _chunks(texts):
                if len(hashes) > REMEMBER:
                    hashes.clear()
                sets = shingle_sets(texts[a:b], k, hashes)
                registers = sketch(sets)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(a, b - a), pa.array([len(s) for s in sets], "i8"),
                        pa.array([xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets], pa.binary()),
                        pa.array([r.tobytes() for r in registers], pa.binary()),
                    ],
                    ["doc_id", "n_shingles", "digest", "registers"],
                )

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, schema)


def _by_likelihood(pairs: DataFrame, nodes: DataFrame, floor: float) -> DataFrame:
    """The pairs (a, b) whose likely similarity is at least floor."""
    side = lambda name: nodes.select(F.col("node").alias(name), F.col("registers").alias(f"r{name}"), F.col("n_shingles").alias(f"n{name}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "ra", "rb", "na", "nb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                ra, rb = (np.frombuffer(b"".join(batch.column(i).to_pylist()), "u2").reshape(-1, M) for i in (2, 3))
                na, nb = (batch.column(i).to_numpy(zero_copy_only=False).astype("f8") for i in (4, 5))
                yield batch.select(["a", "b"]).filter(pa.array(likely_jaccard(ra, rb, na, nb) >= floor))

    return both.mapInArrow(run, both.select("a", "b").schema)


def _confirmed(pairs: DataFrame, sets: DataFrame, per_cent: int) -> DataFrame:
    """The pairs whose full sets are similar enough."""
    side = lambda name: sets.select(F.col("node").alias(name), F.col("shingles").alias(f"s{name}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "sa", "sb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = np.frombuffer(x.as_buffer(), "u8"), np.frombuffer(y.as_buffer(), "u8")
                common = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * common >= per_cent * (len(x) + len(y) - common))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return both.mapInArrow(run, both.select("a", "b").schema)


def full_sets(docs: DataFrame, nodes: DataFrame, k: int, id_col: str, text_col: str) -> DataFrame:
    """(node, shingles as bytes) of the documents named in nodes."""
    wanted = docs.select(F.col(id_col).alias("node"), F.col(text_col).alias("text")).join(nodes, "node", "left_semi")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = _WordHashes()
        for batch in batches:
            texts = [t or b"" for t in batch.column(1).cast(pa.binary()).to_pylist()]
            for a, b in _chunks(texts):
                if len(hashes) > REMEMBER:
                    hashes.clear()
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array([s.tobytes() for s in shingle_sets(texts[a:b], k, hashes)], pa.binary())], ["node", "shingles"])

    return wanted.mapInArrow(run, f"node {docs.schema[id_col].dataType.simpleString()}, shingles binary")


def _links_in_block(left: list[tuple], right: list[tuple] | None, per_cent: int, width: int = 4096) -> list[tuple]:
    """Pairs (a, b) of rows (node, component, shingles) of two chunks, or of one with itself, that are of other
    components and similar enough. Intersections are exact: products of 0/1 matrices over shared shingles, a
    stretch of columns at a time."""
    other = left if right is None else right
    sets = [[np.frombuffer(r[2], "u8") for r in side] for side in (left, other)]
    shared = np.intersect1d(np.unique(np.concatenate(sets[0])), np.unique(np.concatenate(sets[1])), assume_unique=True)
    common = np.zeros((len(left), len(other)), "f4")

    def placed(side: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        owner, value = np.repeat(np.arange(len(side)), [len(x) for x in side]), np.concatenate(side)
        at = np.searchsorted(shared, value)
        known = shared[np.minimum(at, len(shared) - 1)] == value
        return owner[known], at[known]

    if len(shared):
        (row_a, at_a), (row_b, at_b) = placed(sets[0]), placed(sets[1])
        for start in range(0, len(shared), width):
            grids = []
            for rows, at, many in ((row_a, at_a, len(left)), (row_b, at_b, len(other))):
                grid = np.zeros((many, min(width, len(shared) - start)), "f4")
                here = (at >= start) & (at < start + width)
                grid[rows[here], at[here] - start] = 1
                grids.append(grid)
            common += grids[0] @ grids[1].T
    n_a, n_b = (np.array([len(x) for x in side], "f8") for side in sets)
    close = 100 * common.astype("f8") >= per_cent * (n_a[:, None] + n_b[None, :] - common)
    found = []
    for i, j in zip(*(x.tolist() for x in np.nonzero(close)), strict=True):
        a, b = left[i], other[j]
        if a[1] != b[1] and (right is not None or i < j):
            found.append((min(a[0], b[0]), max(a[0], b[0])))
    return found


def _cross_links(members: DataFrame, sets: DataFrame, per_cent: int, weight: int) -> DataFrame:
    """Links between sets of other components among members (hub, node, component, n_shingles) of one hub. The
    members of a hub are dealt into chunks of about ``weight`` shingles and every two chunks meet in a task, so
    no task holds more than two of them; only links come out, never the pairs that were looked at."""
    chunks = members.groupBy("hub").agg((F.floor(F.sum("n_shingles") / weight) + 1).cast("int").alias("chunks"), F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo <> hi")
    dealt = members.join(chunks.select("hub", "chunks"), "hub").withColumn("chunk", F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int"))
    spread = dealt.withColumn("meets", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    spread = spread.join(sets, "node").select("hub", F.least("chunk", "meets").alias("i"), F.greatest("chunk", "meets").alias("j"), "chunk", "node", "component", "shingles")
    keys = ["hub", "i", "j"]
    parts = int(members.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ordered = spread.repartition(parts, *keys).sortWithinPartitions(*keys)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, rows, ids = None, [], None

        def block() -> list[tuple]:
            if key is None or len({r[1] for _, r in rows}) < 2:
                return []
            left, right = [r for c, r in rows if c == key[1]], [r for c, r in rows if c != key[1]]
            if key[1] == key[2]:
                return _links_in_block(left, None, per_cent)
            return _links_in_block(left, right, per_cent) if left and right else []

        out: list[tuple] = []
        for batch in batches:
            ids = batch.schema.field("node").type
            for hub, i, j, chunk, *row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (hub, i, j) != key:
                    out += block()
                    key, rows = (hub, i, j), []
                rows.append((chunk, tuple(row)))
        out += block()
        if ids is not None:
            yield pa.RecordBatch.from_arrays([pa.array([a for a, _ in out], ids), pa.array([b for _, b in out], ids)], ["a", "b"])

    kind = sets.schema["node"].dataType.simpleString()
    return ordered.mapInArrow(run, f"a {kind}, b {kind}").distinct()


def _hot_limit(shared: DataFrame, least: int = 1_000) -> int:
    """Members from which a band is hot: more than a ten-thousandth of all rows, so that 10,000 bands are at most."""
    return max(least, (shared.agg(F.sum("members")).first()[0] or 0) // 10_000)


def _with_shared(buckets: DataFrame, shared: DataFrame, limit: int) -> DataFrame:
    """buckets joined with the table of shared bands. A hot band's rows are spread over many tasks and stay there: hot
    bands are broadcast, the others shuffled."""
    marked = buckets.join(F.broadcast(shared.filter(F.col("members") > limit)), "band", "left")
    cold = marked.filter("hub IS NULL").select("band", "node", "n_shingles").join(shared.filter(F.col("members") <= limit), "band")
    return marked.filter("hub IS NOT NULL").select(cold.columns).unionByName(cold)


def near_duplicates(docs: DataFrame, k: int = 5, per_cent: int = 80, id_col: str = "doc_id", text_col: str = "text", margin: float = 0.17, weight: int = 200_000) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (least id reachable over links of
    intersection / union >= per_cent / 100 on k-word shingle sets) and kept (it is that least id).

    Null, empty and blank texts have no shingles and are linked with nothing. Rows that share an id are one
    document. A row with a null id is linked with nothing, has a null component and is kept. ``margin`` is
    how far below the threshold the likelihood may fall before a pair is given up (five standard errors).
    A set that is not yet connected with all of its band is then compared in full with the rest, in chunks of
    ``weight`` shingles.
    """
    made = settle(sketches(docs, k, id_col, text_col), "sketches")
    full = made.filter(F.col("digest").isNotNull() & F.col("doc_id").isNotNull())
    classes = full.groupBy("digest").agg(F.min("doc_id").alias("node"))
    nodes = settle(full.join(classes, (full["digest"] == classes["digest"]) & (full["doc_id"] == classes["node"]), "inner").select("node", "n_shingles", "registers").dropDuplicates(["node", "registers"]), "nodes")
    buckets = nodes.select("node", "n_shingles", F.explode(bands_of(F.col("registers"))).alias("band"))
    shared = buckets.groupBy("band").agg(F.min("node").alias("hub"), F.count("*").alias("members"), F.min_by("n_shingles", "node").alias("hub_size")).filter("members > 1")
    shared = settle(shared, "bands")
    limit = _hot_limit(shared)
    buckets = settle(_with_shared(buckets, shared, limit), "buckets")
    alike = lambda x, y: (100 * F.least(x, y) >= per_cent * F.greatest(x, y))  # noqa: E731  sizes that allow the similarity
    floor = per_cent / 100 - margin

    # Every set against the least of its band: this joins most groups without looking at their pairs.
    first = buckets.filter((F.col("node") != F.col("hub")) & alike(F.col("n_shingles"), F.col("hub_size"))).select(F.col("hub").alias("a"), F.col("node").alias("b")).distinct()
    first = settle(_by_likelihood(first, nodes, floor), "pairs")
    unresolved = buckets.filter("members > 2").select("band", "node", "n_shingles", "hub", "members")
    wanted = first.select(F.col("a").alias("node")).union(first.select("b")).union(unresolved.select("node")).distinct()
    sets = settle(full_sets(docs, wanted, k, id_col, text_col), "sets")
    links = settle(_confirmed(first, sets, per_cent), "links")
    found = components(links, "a", "b")

    # Sets of one band that are not connected yet, the least aside, which has met them all.
    placed = unresolved.join(found, "node", "left").withColumn("component", F.coalesce("component", "node"))
    mixed = placed.groupBy("band", "members").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo <> hi").select("band", "members")
    hot = F.col("members") > limit
    in_hot = placed.filter(hot).join(F.broadcast(mixed.filter(hot).select("band")), "band", "left_semi")
    in_cold = placed.filter(~hot).join(mixed.filter(~hot).select("band"), "band", "left_semi")
    open_ = in_hot.unionByName(in_cold).filter("node <> hub").select("hub", "node", "component", "n_shingles").distinct()
    more = settle(_cross_links(settle(open_, "open"), sets, per_cent, weight), "links")
    if more.limit(1).count():
        found = components(links.unionByName(more), "a", "b")
    named = classes.join(found, "node", "left").select("digest", F.coalesce("component", "node").alias("component"))
    return made.select("doc_id", "n_shingles", "digest").join(named, "digest", "left").select(
        "doc_id", "n_shingles",
        F.when(F.col("doc_id").isNull(), None).otherwise(F.coalesce("component", "doc_id")).alias("component_id"),
        (F.col("doc_id").isNull() | (F.coalesce("component", "doc_id") == F.col("doc_id"))).alias("kept"),
    )


def keep_one(docs: DataFrame, k: int = 5, per_cent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs, all columns, that near_duplicates() keeps. Of rows that share an id one stays, that of
    least text; rows without an id all stay."""
    gone = near_duplicates(docs, k, per_cent, id_col, text_col).filter("NOT kept").select(F.col("doc_id").alias("gone"))
    left = docs.join(gone, docs[id_col] == gone["gone"], "left_anti")
    repeated = docs.groupBy(F.col(id_col).alias("again")).count().filter("count > 1 AND again IS NOT NULL").select("again")
    if not repeated.limit(1).count():
        return left
    single = left.join(repeated, left[id_col] == repeated["again"], "left_anti")
    several = left.join(repeated, left[id_col] == repeated["again"], "left_semi")
    first, nth = Window.partitionBy(id_col).orderBy(F.col(text_col).asc_nulls_last()), free_name(docs, "_nth")
    return single.unionByName(several.withColumn(nth, F.row_number().over(first)).filter(F.col(nth) == 1).drop(nth))
