"""The match graph: pairs that share tokens, edges above a threshold, clusters."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codematch.operators import score, tokens as tk
from codematch.operators.graph_components import star_components
from codematch.sources.io import discard, materialize


def pair_hits(tokens: DataFrame, min_hits: int = 1, salt: int = 1) -> DataFrame:
    """(a, b, hits), a < b, for items that share a token; a self equi-join, never a list of a token's items.

    salt > 1 deals each token's items over that many tasks and copies the other side to each:
    for tokens so frequent that splitting by the engine is not enough.
    """
    x, y = tokens.select(F.col("id").alias("a"), "token"), tokens.select(F.col("id").alias("b"), "token")
    keys = ["token"]
    if salt > 1:
        x = x.withColumn("salt", F.pmod(F.xxhash64("a"), F.lit(salt)))
        y = y.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salt - 1).cast("long"))))
        keys.append("salt")
    met = x.join(y, keys).where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("hits"))
    return met.where(F.col("hits") >= min_hits) if min_hits > 1 else met


def pair_hits_naive(codes: DataFrame, m: int) -> DataFrame:
    """The same by comparing all pairs: the check for small inputs that grouping by token avoids."""
    x, y = codes.alias("x"), codes.alias("y")
    met = x.join(y, F.col("x.id") < F.col("y.id")).select(F.col("x.id").alias("a"), F.col("y.id").alias("b"), score.hits_pair("x", "y", m).cast("long").alias("hits"))
    return met.where("hits > 0")


def pair_hits_prefix(tokens: DataFrame, m: int, min_hits: int) -> DataFrame:
    """Exactly the pairs with min_hits or more, from fewer joined rows.

    In one order of all tokens, rarest first, two items with h equal tokens of m share one
    among the first m - h + 1 of each. Candidates meet on these only, and are then counted.
    """
    n = tk.frequencies(tokens)
    ranked = tokens.join(n, "token").withColumn("at", F.row_number().over(Window.partitionBy("id").orderBy("n", "token")))
    first = ranked.where((F.col("at") <= m - min_hits + 1) & (F.col("n") > 1)).select("id", "token")
    x, y = first.select(F.col("id").alias("a"), "token"), first.select(F.col("id").alias("b"), "token")
    pairs = x.join(y, "token").where("a < b").select("a", "b").distinct()
    own = tokens.groupBy("id").agg(F.collect_list("token").alias("t"))  # m tokens an item
    both = pairs.join(own.select(F.col("id").alias("a"), F.col("t").alias("s")), "a").join(own.select(F.col("id").alias("b"), "t"), "b")
    return both.select("a", "b", F.size(F.array_intersect("s", "t")).cast("long").alias("hits")).where(F.col("hits") >= min_hits)


def pair_hits_blocks(codes: DataFrame, m: int, min_hits: int) -> DataFrame:
    """The pairs with min_hits or more of m equal tokens, over all tokens however frequent, without a stoplist.

    Such a pair differs in m - min_hits places at most, so of one block more than that at
    least one is equal throughout. Pairs meet on equal blocks, in the first such block only,
    and their hits are counted there; keys are hashes, which can add candidates but no pairs.
    """
    n = m - min_hits + 1
    if not 1 <= n <= m:
        raise ValueError(f"min_hits must be 1 to {m}")
    at = [i * m // n for i in range(n + 1)]
    half = m // 2
    one = codes.select("id", "c1", F.coalesce("c2", "c1").alias("c2"), "fine")
    first, second = F.col("c1"), F.col("c2")
    keys = [F.xxhash64(F.lit(i), *([first] if a < half else []), *([second] if b > half else []), F.slice("fine", a + 1, b - a)) for i, (a, b) in enumerate(zip(at, at[1:], strict=False))]
    rows = one.withColumn("keys", F.array(*keys)).select("*", F.posexplode("keys").alias("block", "key"))
    x, y = rows.alias("x"), rows.alias("y")
    earlier = F.exists(F.zip_with(F.slice("x.keys", F.lit(1), F.col("x.block")), F.slice("y.keys", F.lit(1), F.col("x.block")), lambda p, q: p == q), lambda e: e)
    hits = score.hits_pair("x", "y", m).cast("long")
    met = x.join(y, (F.col("x.key") == F.col("y.key")) & (F.col("x.block") == F.col("y.block")) & (F.col("x.id") < F.col("y.id"))).where((hits >= min_hits) & ~earlier)
    return met.select(F.col("x.id").alias("a"), F.col("y.id").alias("b"), hits.alias("hits"))


def links(codes: DataFrame, m: int, t: int, strict: bool = True, broadcast_up_to: int = 100_000) -> DataFrame:
    """(a, b) with the components of all pairs of more than t equal tokens (t or more if not strict), t < m.

    Items of equal codes are one class and tied to its smallest id, so n copies make n - 1
    rows; only the classes meet in pairs.
    """
    least = t + 1 if strict else t
    own = codes.select("id", "c1", F.coalesce("c2", "c1").alias("c2"), "fine")
    classes = materialize(own.groupBy("c1", "c2", "fine").agg(F.min("id").alias("rep"), F.countDistinct("id").alias("n")), "classes")
    more = classes.where("n > 1").drop("n")
    more = F.broadcast(more) if more.limit(broadcast_up_to + 1).count() <= broadcast_up_to else more
    same = own.join(more, ["c1", "c2", "fine"]).where("id <> rep").select(F.col("rep").alias("a"), F.col("id").alias("b"))
    return pair_hits_blocks(classes.withColumnRenamed("rep", "id"), m, least).select("a", "b").unionAll(same)


def edges(pairs: DataFrame, t: int, strict: bool = True) -> DataFrame:
    """Pairs with more than t hits; with t or more if not strict."""
    return pairs.where(F.col("hits") > t if strict else F.col("hits") >= t)


def label_components(pairs: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Components by the least label of neighbours, with a jump to the label's label each round."""
    both = pairs.select("a", "b").unionAll(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()
    both = materialize(both, "label-edges")
    now = materialize(both.select(F.col("a").alias("id")).distinct().withColumn("component", F.col("id")), "labels")
    for _ in range(max_rounds):
        near = both.join(now.withColumnRenamed("id", "b"), "b").groupBy("a").agg(F.min("component").alias("near"))
        step = now.join(near, now.id == near.a).select("id", F.least("component", "near").alias("component"))
        jump = step.alias("s").join(now.alias("o"), F.col("s.component") == F.col("o.id")).select("s.id", F.least("s.component", "o.component").alias("component"))
        after = materialize(jump, "labels")
        moved = after.alias("x").join(now.alias("y"), "id").where("x.component <> y.component").limit(1).count()
        discard(now)
        now = after
        if not moved:
            return now
    raise RuntimeError("components did not settle")


def union_find(pairs: list[tuple[int, int]]) -> dict[int, int]:
    """id -> least id of its component."""
    up: dict[int, int] = {}

    def root(x: int) -> int:
        up.setdefault(x, x)
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for a, b in pairs:
        a, b = root(a), root(b)
        if a != b:
            up[max(a, b)] = min(a, b)
    return {x: root(x) for x in list(up)}


LOCAL_EDGES = 100_000


def local_components(pairs: DataFrame, limit: int = LOCAL_EDGES) -> DataFrame:
    """Components of a small graph in one task; an error beyond a checked number of edges."""
    if pairs.limit(limit + 1).count() > limit:
        raise ValueError(f"more than {limit} edges: use the star method")

    def run(table: pa.Table) -> pa.Table:
        found = union_find(list(zip(table.column("a").to_pylist(), table.column("b").to_pylist(), strict=True)))
        return pa.table({"id": pa.array(list(found), pa.int64()), "component": pa.array(list(found.values()), pa.int64())})

    return pairs.select("a", "b", F.lit(0).alias("g")).groupBy("g").applyInArrow(lambda t: run(t), "id long, component long")


def components(pairs: DataFrame, nodes: DataFrame | None = None, method: str = "star") -> DataFrame:
    """(id, component = least id); with nodes(id) every node is there, alone if no edge touches it.

    The local method is for up to LOCAL_EDGES edges; more go to star contractions, which give the same components.
    """
    if method == "local" and pairs.limit(LOCAL_EDGES + 1).count() > LOCAL_EDGES:
        method = "star"
    found = {"star": star_components, "label": label_components, "local": local_components}[method](pairs)
    if nodes is None:
        return found
    return nodes.select("id").distinct().join(found, "id", "left").select("id", F.coalesce("component", "id").alias("component"))


def cluster(tokens: DataFrame, t: int = 3, lo: int = 10, hi: int = 10_000, strict: bool = True, method: str = "star") -> DataFrame:
    """The whole chain: stop frequent and rare tokens, count pairs, keep edges, find components of all items."""
    kept = tk.stoplist(tokens, lo, hi)
    linked = materialize(edges(pair_hits(kept), t, strict), "edges")
    return components(linked, tokens.select("id").distinct(), method)


def cluster_all(codes: DataFrame, m: int, t: int, strict: bool = True, method: str = "star") -> DataFrame:
    """The chain without a stoplist: components of all items by every pair of more than t equal tokens."""
    codes = materialize(codes.select("id", "c1", "c2", "fine"), "codes")
    return components(materialize(links(codes, m, t, strict), "edges"), codes.select("id").distinct(), method)


def noisy_labels(found: DataFrame, lo: int = 100, hi: int = 10_000) -> DataFrame:
    """(id, pseudo_label) of the items of mid-size clusters."""
    mid = found.groupBy("component").agg(F.count(F.lit(1)).alias("n")).where((F.col("n") >= lo) & (F.col("n") <= hi))
    return found.join(mid, "component", "left_semi").select("id", F.col("component").alias("pseudo_label"))


def dedup_results(results: DataFrame, codes: DataFrame, m: int, t: int, strict: bool = True, keep: str = "best_rank") -> DataFrame:
    """(qid, id, rnk, component, kept, dup_of) for result lists (qid, id, rnk).

    Within each list, items with more than t equal tokens are linked; a component is named by
    its member that stays: the best ranked, with keep="smallest_id" the smallest, with
    keep="longest" the one with the largest results.length. A list is bounded by its depth, so
    each is one group; lists are dealt by query.
    """
    length = F.col("length") if keep == "longest" else F.lit(0)
    rows = results.withColumn("length", length.cast("long")).join(codes.select("id", "c1", "c2", "fine"), "id").select("qid", "id", "rnk", "length", "c1", "c2", "fine")

    def run(table: pa.Table) -> pa.Table:
        rows, name = dedup_list(table.to_pylist(), m, t, strict, keep)
        return pa.table({"qid": pa.array([r["qid"] for r in rows], pa.int64()), "id": pa.array([r["id"] for r in rows], pa.int64()), "rnk": pa.array([r["rnk"] for r in rows], pa.int32()), "component": pa.array([rows[c]["id"] for c in name], pa.int64()), "kept": pa.array([c == i for i, c in enumerate(name)]), "dup_of": pa.array([None if c == i else rows[c]["id"] for i, c in enumerate(name)], pa.int64())})

    return rows.groupBy("qid").applyInArrow(lambda t: run(t), "qid long, id long, rnk int, component long, kept boolean, dup_of long")


ORDERS = {"best_rank": lambda r: (r["rnk"], r["id"]), "smallest_id": lambda r: (r["id"],), "longest": lambda r: (-(r["length"] or 0), r["id"])}


def dedup_list(rows: list[dict], m: int, t: int, strict: bool = True, keep: str = "best_rank") -> tuple[list[dict], list[int]]:
    """The items of one result list (id, rnk, c1, c2, fine), in the order of the policy, and for each the place of the one that stays for it.

    Plain code for a list that a service holds in memory: no Spark job.
    """
    rows = sorted(rows, key=ORDERS[keep])
    posting: dict = {}
    for i, r in enumerate(rows):
        for p, f in enumerate(r["fine"]):
            posting.setdefault((r["c1"] if p < m // 2 or r["c2"] is None else r["c2"], p, f), []).append(i)
    n: dict = {}
    for own in posting.values():
        for x, i in enumerate(own):
            for j in own[x + 1 :]:
                n[i, j] = n.get((i, j), 0) + 1
    found = union_find([p for p, k in n.items() if k > t or (not strict and k == t)])
    return rows, [found.get(i, i) for i in range(len(rows))]
