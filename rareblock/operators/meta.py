"""Meta-blocking: pairs weighted by the blocks they share, then pruned.

Records of equal keys are one class: edges are made and weighed between classes, in numbers of records, and laid out as
pairs of records at the end. Of blocks up to a cap; ``purge=None`` asks for all blocks, whose edges grow with the square of
the classes in the largest. broadcast_edges() is the published form, which sends every record's keys to all workers: that map
grows with the records, so it is refused beyond a size, where the form reported ran out of memory.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.storage import settle
from . import keys as block_keys

WEIGHTS = ("cbs", "ecbs", "js", "ejs", "arcs", "chi2")
PRUNES = ("wep", "cep", "wnp", "rwnp", "cnp", "rcnp", "local_max")
PURGE = 500
#: Pairs of records in an edge (rid1, rid2, n1, n2) between classes, or of a class with itself.
PAIRS = "if(rid1 = rid2, n1 * (n1 - 1) div 2, n1 * n2)"
#: Most records whose ids are sent to every task when edges are laid out; beyond, they are joined by a shuffle.
SENT = 2_000_000
#: Mean keys of a record up to which pairs are counted inside blocks.
FEW = 16


def classes(index: DataFrame) -> DataFrame:
    """(rid, keys, n, members) of an index: one row per set of keys, named by the least of its records; a written table."""
    held = index.groupBy(F.array_sort("keys").alias("keys")).agg(F.array_sort(F.collect_list("rid")).alias("members"))
    return settle(held.select(F.col("members")[0].alias("rid"), "keys", F.size("members").cast("bigint").alias("n"), "members"), "classes")


def lay_out(edge: DataFrame, held: DataFrame) -> DataFrame:
    """Edges (rid1, rid2, n1, n2, ...) between classes as pairs of their records, rid1 < rid2."""
    records, most = held.agg(F.sum("n"), F.max("n")).first()
    kept = [c for c in edge.columns if c not in ("rid1", "rid2", "n1", "n2")]
    if (most or 0) < 2:
        return edge.select("rid1", "rid2", *kept)
    hint = F.broadcast if records <= SENT else (lambda df: df)
    side = lambda i: hint(held.select(F.col("rid").alias(f"rid{i}"), F.col("members").alias(f"m{i}")))
    first = edge.join(side(1), "rid1").join(side(2), "rid2").select((F.col("rid1") == F.col("rid2")).alias("own"), F.explode("m1").alias("a"), "m2", *kept)
    both = first.select("own", "a", F.explode("m2").alias("b"), *kept).filter("NOT own OR a < b")
    return both.select(F.least("a", "b").alias("rid1"), F.greatest("a", "b").alias("rid2"), *kept)


def block_postings(index: DataFrame, purge: int | None = PURGE, ratio: float | None = None) -> DataFrame:
    """(rid, key, size) of blocks of two records at least: those above ``purge`` records dropped, then each
    record kept in the smallest ``ratio`` of its blocks, rounded up; ties by key. Of classes, (rid, key, size, n): sizes are of
    records."""
    n, many = (["n"], F.sum("n")) if "n" in index.columns else ([], F.count("*"))
    post = index.select("rid", *n, F.explode("keys").alias("key"))
    sizes = post.groupBy("key").agg(many.alias("size")).filter("size > 1")
    if purge:
        sizes = sizes.filter(F.col("size") <= purge)
    out = post.join(sizes, "key").select("rid", "key", "size", *n)
    if ratio:
        out = smallest(out, ratio)
        again = out.groupBy("key").agg(many.alias("size")).filter("size > 1")
        out = out.drop("size").join(again, "key").select("rid", "key", "size", *n)
    return out


def smallest(post: DataFrame, ratio: float) -> DataFrame:
    """Of postings (rid, key, size, ...) each record's in the smallest ``ratio`` of its blocks, rounded up; ties by key."""
    mine = Window.partitionBy("rid")
    return post.withColumns({"nth": F.row_number().over(mine.orderBy("size", "key")), "all": F.count("*").over(mine)}).filter(F.col("nth") <= F.ceil(F.col("all") * ratio)).drop("nth", "all")


def _grouped(post: DataFrame) -> DataFrame:
    """(rid1, rid2, n1, n2, c, arcs) of every pair in a block; pairs are shuffled, once for each block they share."""
    side = lambda i: post.select(F.col("rid").alias(f"rid{i}"), F.col("n").alias(f"n{i}"), "key", "size")
    both = side(1).join(side(2).drop("size"), "key").filter("rid1 < rid2 OR rid1 = rid2 AND n1 > 1")
    return both.groupBy("rid1", "rid2").agg(F.count("*").cast("double").alias("c"), F.sum(F.lit(2.0) / (F.col("size") * (F.col("size") - 1))).alias("arcs"), F.min("n1").alias("n1"), F.min("n2").alias("n2"))


def _inside(post: DataFrame) -> DataFrame:
    """_grouped() where no pair is shuffled: postings take their record's keys, numbered, into the block, and a pair
    counts in the least block that both share."""
    numbers = settle(post.select("key").distinct().withColumn("at", F.monotonically_increasing_id()), "numbers")
    share = F.lit(2.0) / (F.col("size") * (F.col("size") - 1))
    held = post.join(numbers, "key").groupBy("rid").agg(F.min("n").alias("n"), F.collect_list("at").alias("k"), F.map_from_entries(F.collect_list(F.struct("at", share))).alias("s"))
    parts = int(post.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # named, for few postings make many pairs
    side = lambda i: held.select(F.explode("k").alias("at"), *[F.col(c).alias(f"{c}{i}") for c in ("rid", "n", "k", "s")]).repartition(parts, "at")
    both = side(1).join(side(2).drop("s2"), "at").filter("rid1 < rid2 OR rid1 = rid2 AND n1 > 1").withColumn("common", F.array_intersect("k1", "k2"))
    arcs = F.aggregate("common", F.lit(0.0), lambda total, at: total + F.col("s1")[at])
    return both.filter(F.array_min("common") == F.col("at")).select("rid1", "rid2", "n1", "n2", F.size("common").cast("double").alias("c"), arcs.alias("arcs"))


def edges(post: DataFrame, weight: str = "cbs") -> DataFrame:
    """(rid1, rid2, w) of every pair that shares a block, w rounded to nine places so that ties are ties. Of postings
    of classes, (rid1, rid2, n1, n2, w), those of a class with itself among them."""
    ns = ["n1", "n2"] if "n" in post.columns else []
    post = post if ns else post.withColumn("n", F.lit(1).cast("bigint"))
    entries, records = post.agg(F.count("*"), F.approx_count_distinct("rid")).first()
    pairs = (_inside if entries <= FEW * max(1, records) else _grouped)(post)
    if weight in ("cbs", "arcs"):
        return pairs.select("rid1", "rid2", *ns, F.round(F.col("c" if weight == "cbs" else "arcs"), 9).alias("w"))
    mine = post.groupBy("rid").agg(F.count("*").cast("double").alias("b"))
    deg = lambda name, to: mine.select(F.col("rid").alias(name), F.col("b").alias(to))
    full = pairs.join(deg("rid1", "b1"), "rid1").join(deg("rid2", "b2"), "rid2")
    c, b1, b2 = F.col("c"), F.col("b1"), F.col("b2")
    js = c / (b1 + b2 - c)
    if weight == "js":
        w: Column = js
    elif weight == "ejs":
        ends = _ends(pairs).groupBy("node").agg(F.sum("far").cast("double").alias("d")).withColumnRenamed("node", "rid")
        far = lambda name, to: ends.select(F.col("rid").alias(name), F.col("d").alias(to))
        total = pairs.agg(F.sum(F.expr(PAIRS)).cast("double").alias("e"))
        full = full.join(far("rid1", "d1"), "rid1").join(far("rid2", "d2"), "rid2").crossJoin(F.broadcast(total))  # one row
        w = js * F.log(F.col("e") / F.col("d1")) * F.log(F.col("e") / F.col("d2"))
    else:
        blocks = post.agg(F.count_distinct("key").cast("double").alias("n"))
        full = full.crossJoin(F.broadcast(blocks))  # one row
        n = F.col("n")
        if weight == "ecbs":
            w = c * F.log(n / b1) * F.log(n / b2)
        elif weight == "chi2":
            off = c * (n - b1 - b2 + c) - (b1 - c) * (b2 - c)
            under = b1 * b2 * (n - b1) * (n - b2)
            w = F.when(under > 0, n * off * off / F.when(under > 0, under)).otherwise(0.0)
        else:
            raise ValueError(f"weight must be one of {WEIGHTS}")
    return full.select("rid1", "rid2", *ns, F.round(w, 9).alias("w"))


def _ends(edge: DataFrame) -> DataFrame:
    """(node, far, ...): either end of edges between classes, with the records at the other end of one of its own."""
    end = lambda node, far: F.struct(F.col(node).alias("node"), far.alias("far"))
    both = F.when(F.col("rid1") == F.col("rid2"), F.array(end("rid1", F.col("n1") - 1))).otherwise(F.array(end("rid1", F.col("n2")), end("rid2", F.col("n1"))))
    return edge.withColumn("end", F.explode(both)).select("end.node", "end.far", *edge.columns)


def _kth(df: DataFrame, c: Column, k: int, ways: int = 1024, many: Column | None = None) -> tuple[object, int]:
    """(value of c in the k-th row in its order, rows with less): by counts in ever narrower ranges, so that no task
    sorts and the driver sees ``ways`` rows at a time. A row counts as ``many`` says, an aggregate; else once."""
    many = F.count("*") if many is None else many
    low, high = df.agg(F.min(c), F.max(c)).first()
    before = 0
    while low < high:
        way = F.least(F.lit(ways - 1), F.floor((c - low) / (F.lit(high) - low) * ways))
        inside = df.filter(c.between(low, high)).groupBy(way.alias("way")).agg(many.alias("rows"), F.min(c).alias("low"), F.max(c).alias("high"))
        for r in sorted(inside.collect(), key=lambda r: r["way"]):
            low, high = r["low"], r["high"]
            if before + r["rows"] >= k:
                break
            before += r["rows"]
    return low, before


def _first_rows(edge: DataFrame, k: int) -> DataFrame:
    """The first k edges in the order of (w desc, rid1, rid2): those above the weight of the k-th, and of its ties those
    of less ids."""
    if k <= 0:
        return edge.filter("false")
    if edge.count() <= k:
        return edge
    keep, ties = F.lit(False), F.lit(True)
    for c in (-F.col("w"), F.col("rid1"), F.col("rid2")):
        value, before = _kth(edge.filter(ties), c, k)
        keep, ties, k = keep | (ties & (c < value)), ties & (c == value), k - before
    return edge.filter(keep | ties)


def _first_pairs(edge: DataFrame, k: int, held: DataFrame) -> DataFrame:
    """_first_rows() of the pairs of records of edges between classes: the weight of the k-th is found in numbers of
    records, and only its ties are laid out to be counted."""
    many = F.sum(F.expr(PAIRS))
    if k <= 0 or (edge.agg(many).first()[0] or 0) <= k:
        return lay_out(edge if k > 0 else edge.filter("false"), held)
    value, before = _kth(edge, -F.col("w"), k, many=many)
    above, tied = (lay_out(edge.filter(kept), held) for kept in (-F.col("w") < value, -F.col("w") == value))
    return above.unionByName(_first_rows(tied, k - before))


def prune(edge: DataFrame, how: str, post: DataFrame, held: DataFrame, divisor: float = 4.0) -> DataFrame:
    """Pairs that stay, of edges and postings of classes. wep: weight at least the mean. cep: the best half as many pairs as
    there are postings. wnp / cnp: at least the mean, or among the best k, of either end's; rwnp / rcnp: of both ends'.
    local_max: at least (greatest weight at one end + at the other) / divisor. Ties by (w desc, rid1, rid2)."""
    return _best(edge, how, post, held) if how in ("cep", "cnp", "rcnp") else lay_out(above_bars(edge, how, divisor), held)


def above_bars(edge: DataFrame, how: str, divisor: float = 4.0) -> DataFrame:
    """Edges between classes that stay where weights are held against means or maxima, which a class's records share."""
    if how == "wep":
        mean = edge.agg(F.round(F.sum(F.col("w") * F.expr(PAIRS)) / F.sum(F.expr(PAIRS)), 9).alias("mean"))
        return edge.crossJoin(F.broadcast(mean)).filter("w >= mean").drop("mean")  # one row
    if how not in ("wnp", "rwnp", "local_max"):
        raise ValueError(f"prune must be one of {PRUNES}")
    value = F.max("w") if how == "local_max" else F.round(F.sum(F.col("w") * F.col("far")) / F.sum("far"), 9)
    bar = _ends(edge).groupBy("node").agg(value.alias("bar"))
    at = lambda name: bar.select(F.col("node").alias(f"rid{name}"), F.col("bar").alias(f"bar{name}"))
    both = edge.join(at(1), "rid1").join(at(2), "rid2")
    ok = {"wnp": "w >= bar1 OR w >= bar2", "rwnp": "w >= bar1 AND w >= bar2", "local_max": f"w >= (bar1 + bar2) / {divisor}"}[how]
    return both.filter(ok).select("rid1", "rid2", "n1", "n2", "w")


def _best(edge: DataFrame, how: str, post: DataFrame, held: DataFrame) -> DataFrame:
    postings = post.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    edge = settle(edge, "edges")
    if how == "cep":
        return _first_pairs(edge, postings // 2, held)
    nodes = edge.select(F.explode(F.array("rid1", "rid2")).alias("rid")).distinct().join(held, "rid").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    ends = lay_out(edge, held).select(F.explode(F.array("rid1", "rid2")).alias("node"), "rid1", "rid2", "w")
    k = max(1, postings // max(1, nodes) - 1)
    best = ends.withColumn("nth", F.row_number().over(Window.partitionBy("node").orderBy(F.desc("w"), "rid1", "rid2"))).filter(F.col("nth") <= k)
    return best.groupBy("rid1", "rid2", "w").agg(F.count("*").alias("ends")).filter("ends = 2" if how == "rcnp" else "ends >= 1").drop("ends")


def weighted(index: DataFrame, weight: str = "cbs", purge: int | None = PURGE) -> DataFrame:
    """edges() of a record index, made between its classes."""
    held = classes(index)
    return lay_out(edges(block_postings(held, purge), weight), held)


def meta_blocking(index: DataFrame, weight: str = "cbs", how: str = "wnp", purge: int | None = PURGE, ratio: float | None = None) -> DataFrame:
    """(rid1, rid2) after purging, filtering, weighting and pruning."""
    held = classes(index)
    post = block_postings(held, purge, ratio)
    return prune(edges(post, weight), how, post, held).select("rid1", "rid2")


def broadcast_edges(index: DataFrame, purge: int | None = PURGE, most_bytes: int = 256 * 2**20) -> DataFrame:
    """edges() with weight cbs as published: blocks are expanded to pairs and both records' keys are looked up in a map
    sent to every worker, which a pair's least common block then counts once. MemoryError where the map is too large."""
    held = classes(index)
    post = block_postings(held, purge)
    entries, records = post.agg(F.count("*"), F.count_distinct("rid")).first()
    needed = entries * 16 + records * 64
    if needed > most_bytes:
        raise MemoryError(f"the keys of {records} sets of keys take {needed} bytes on every worker; use edges()")
    keys_of = post.groupBy("rid").agg(F.collect_set("key").alias("keys"))
    blocks = post.groupBy("key").agg(F.array_sort(F.collect_list(F.struct("rid", "n"))).alias("m"))
    first = blocks.select("key", "m", F.posexplode("m").alias("i", "a"))
    pairs = first.select("key", "a", F.explode(F.slice("m", F.col("i") + 1, F.size("m"))).alias("b")).filter("a.rid < b.rid OR a.n > 1")
    pairs = pairs.select("key", F.col("a.rid").alias("rid1"), F.col("a.n").alias("n1"), F.col("b.rid").alias("rid2"), F.col("b.n").alias("n2"))
    side = lambda n: F.broadcast(keys_of.select(F.col("rid").alias(f"rid{n}"), F.col("keys").alias(f"k{n}")))
    common = F.array_intersect("k1", "k2")
    once = pairs.join(side(1), "rid1").join(side(2), "rid2").filter(F.array_min(common) == F.col("key"))
    return lay_out(once.select("rid1", "rid2", "n1", "n2", F.size(common).cast("double").alias("w")), held)
