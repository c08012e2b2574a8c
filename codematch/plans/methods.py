"""Methods of the library as queries, each with the SQL an independent engine runs."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codematch.operators import blocks, encode as en, graph, metrics, model as md, prep, querysets, score, search, tokens as tk, vectors
from codematch.operators.kmeans import lloyd_rounds
from codematch.plans import sql
from codematch.sources.io import materialize

K, M, KS = 8, 8, 16
#: Parameters of the document model.
DK, DM, DKS = 16, 16, 32
QUOTA, DEPTH = 50, 20
_QUERY = "id % 10 = 0"

Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, text: str | None = None):
    def add(f):
        Q[name] = f
        if text is not None:
            SQL[name] = text
        return f

    return add


def emb(spark: SparkSession, sf: str) -> DataFrame:
    return vectors.embeddings(spark, sf)


def anchor(spark, sf, view="embeddings", K=K, m=M, k=KS, **how):
    df = vectors.VIEWS[view](spark, sf)
    return df, md.anchor(df, K, m, k, **how)


def pq_model(spark, sf, m=M, k=KS) -> md.CodeModel:
    """A plain product quantizer: one coarse cluster at 0; sub-centroid j of a block is that block of the j-th row."""
    x = np.array([r.vec for r in sorted(emb(spark, sf).orderBy("id").limit(k).collect())])
    d = x.shape[1]
    return md.CodeModel(m=m, coarse=np.zeros((1, 1, d)), sub=x.reshape(k, m, d // m).transpose(1, 0, 2))


_C = sql.codes("embeddings", K, M, KS)
_T = _C + ",\n" + sql.tokens(M)
_PQ = f"""v AS (SELECT id, vec, row_number() OVER (ORDER BY id) - 1 AS r FROM ({sql.vec('embeddings')})),
bk AS (SELECT id, r, b, vec[b * 8 + 1 : (b + 1) * 8] AS part FROM v CROSS JOIN (SELECT unnest(range({M})) AS b)),
sd AS (SELECT x.id, x.b, y.r AS j, {sql.square('x.part', 'y.part', 8)} AS e FROM bk x JOIN bk y ON x.b = y.b AND y.r < {KS}),
fc AS (SELECT id, b, j, e FROM (SELECT *, row_number() OVER (PARTITION BY id, b ORDER BY e, j) AS rn FROM sd) WHERE rn = 1)"""


@query("nearest_centroid", f"WITH {_C} SELECT id, CAST(h AS INTEGER) AS half, CAST(c AS INTEGER) AS c, round(d, 6) AS d FROM cr WHERE rn = 1")
def nearest_centroid(spark, sf):
    df, model = anchor(spark, sf)
    return en.coarse_codes(df, model).select("id", "half", "c", F.round("d", 6).alias("d"))


def _rounds_sql(rounds: int) -> str:
    parts = [f"v AS ({sql.vec('embeddings')})", f"c0 AS (SELECT row_number() OVER (ORDER BY id) - 1 AS idx, vec AS cv FROM v QUALIFY row_number() OVER (ORDER BY id) <= {K})"]
    for i in range(1, rounds + 1):
        parts.append(f"a{i} AS (SELECT id, vec, idx FROM (SELECT v.id, v.vec, c.idx, row_number() OVER (PARTITION BY v.id ORDER BY {sql.square('v.vec', 'c.cv', 64)}, c.idx) AS rn FROM v CROSS JOIN c{i - 1} c) WHERE rn = 1)")
        parts.append(f"m{i} AS (SELECT idx, i, avg(vec[i]) AS x FROM a{i} CROSS JOIN (SELECT unnest(range(1, 65)) AS i) GROUP BY 1, 2)")
        parts.append(f"c{i} AS (SELECT o.idx, coalesce(n.cv, o.cv) AS cv FROM c{i - 1} o LEFT JOIN (SELECT idx, list(x ORDER BY i) AS cv FROM m{i} GROUP BY idx) n USING (idx))")
    return "WITH " + ",\n".join(parts) + f" SELECT CAST(idx AS INTEGER) AS idx, CAST(i - 1 AS INTEGER) AS dim, round(cv[i], 6) AS x FROM c{rounds} CROSS JOIN (SELECT unnest(range(1, 65)) AS i)"


def _rounds(n: int):
    def run(spark, sf):
        df = emb(spark, sf)
        start = np.array([r.vec for r in sorted(df.orderBy("id").limit(K).collect())])
        book, _ = lloyd_rounds(df, start[None], n)
        return spark.createDataFrame([(i, j, float(np.round(x, 6))) for i, row in enumerate(book[0]) for j, x in enumerate(row)], "idx int, dim int, x double")

    return run


for _n in (1, 2):
    query(f"kmeans_round{_n}", _rounds_sql(_n))(_rounds(_n))


@query("pq_train_round1", f"WITH {_PQ}, mv AS (SELECT fc.b, fc.j, i, avg(bk.part[i]) AS x FROM fc JOIN bk ON bk.id = fc.id AND bk.b = fc.b CROSS JOIN (SELECT unnest(range(1, 9)) AS i) GROUP BY 1, 2, 3) SELECT CAST(b AS INTEGER) AS block, CAST(j AS INTEGER) AS idx, CAST(i - 1 AS INTEGER) AS dim, round(x, 6) AS x FROM mv")
def pq_train_round1(spark, sf):
    model = pq_model(spark, sf)
    book, counts = lloyd_rounds(emb(spark, sf), model.sub, 1)
    return spark.createDataFrame([(b, j, i, float(np.round(x, 6))) for b in range(M) for j in range(KS) if counts[b, j] for i, x in enumerate(book[b, j])], "block int, idx int, dim int, x double")


@query("pq_encode", f"WITH {_PQ} SELECT id, list(CAST(j AS SMALLINT) ORDER BY b) AS fine FROM fc GROUP BY id")
def pq_encode(spark, sf):
    return en.encode(emb(spark, sf), pq_model(spark, sf)).select("id", "fine")


@query("pq_decode", f"WITH {_PQ} SELECT fc.id, CAST(fc.b AS INTEGER) AS block, round(list_sum(bk.part), 6) AS total, round(fc.e, 6) AS error FROM fc JOIN bk ON bk.b = fc.b AND bk.r = fc.j")
def pq_decode(spark, sf):
    model, df = pq_model(spark, sf), emb(spark, sf)

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            x = en.matrix(batch, 1, model.d)
            c, f = model.encode(x)
            y = model.decode(c, f).reshape(len(x), M, -1)
            e = ((x.reshape(y.shape) - y) ** 2).sum(2)
            n = len(x)
            yield pa.RecordBatch.from_pydict({"id": np.repeat(batch.column(0).to_numpy(), M), "block": np.tile(np.arange(M, dtype=np.int32), n), "total": y.sum(2).ravel(), "error": e.ravel()})

    return df.select("id", "vec").mapInArrow(run, "id long, block int, total double, error double").select("id", "block", F.round("total", 6).alias("total"), F.round("error", 6).alias("error"))


@query("sdc_scan", f"""WITH {_PQ}, t AS (SELECT x.b, x.r AS i, y.r AS j, {sql.square('x.part', 'y.part', 8)} AS e FROM bk x JOIN bk y ON x.b = y.b AND x.r < {KS} AND y.r < {KS})
SELECT q.id AS qid, x.id, round(sum(t.e), 6) AS dist FROM fc q JOIN fc x ON q.b = x.b JOIN t ON t.b = q.b AND t.i = q.j AND t.j = x.j WHERE q.id % 50 = 0 GROUP BY 1, 2""")
def sdc_scan(spark, sf):
    model = pq_model(spark, sf)
    codes = en.encode(emb(spark, sf), model)
    q = codes.where("id % 50 = 0").select(F.col("id").alias("qid"), F.col("fine").alias("qf"))
    return F.broadcast(q).crossJoin(codes).select("qid", "id", F.round(score.sdc(F.col("qf"), F.col("fine"), score.sdc_tables(model)), 6).alias("dist"))


@query("adc_scan", f"WITH {_PQ} SELECT q.id AS qid, x.id, round(sum({sql.square('q.part', 's.part', 8)}), 6) AS dist FROM bk q JOIN fc x ON q.b = x.b JOIN bk s ON s.b = x.b AND s.r = x.j WHERE q.id % 50 = 0 GROUP BY 1, 2")
def adc_scan(spark, sf):
    model, df = pq_model(spark, sf), emb(spark, sf)
    q = score.adc_tables(df.where("id % 50 = 0"), model)
    return F.broadcast(q).crossJoin(en.encode(df, model)).select("qid", "id", F.round(score.adc(F.col("table"), F.col("fine"), M, KS), 6).alias("dist"))


_ONE = sql.codes("embeddings", K, M, KS, halves=1)


@query("single_coarse_encode", f"WITH {_ONE} SELECT id, c1, fine FROM codes")
def single_coarse_encode(spark, sf):
    df, model = anchor(spark, sf, halves=1)
    return en.encode(df, model).select("id", "c1", "fine")


def _single_hits(codes):
    x, y = codes.alias("x"), codes.alias("y")
    return x.join(y, (F.col("x.c1") == F.col("y.c1")) & (F.col("x.id") < F.col("y.id"))).select(F.col("x.id").alias("a"), F.col("y.id").alias("b"), score.hits_single("x", "y", M).alias("hits")).where("hits > 0")


_HITS_ONE = f"SELECT a, b, CAST(hits AS INTEGER) AS hits FROM (SELECT x.id AS a, y.id AS b, {sql.hits('x.fine', 'y.fine', M)} AS hits FROM codes x JOIN codes y ON x.c1 = y.c1 AND x.id < y.id) WHERE hits > 0"


@query("single_coarse_hits", f"WITH {_ONE} {_HITS_ONE}")
def single_coarse_hits(spark, sf):
    df, model = anchor(spark, sf, halves=1)
    return _single_hits(en.encode(df, model))


@query("local_codebook_hits", f"WITH {sql.codes('embeddings', K, M, 8, halves=1, local=True)} {_HITS_ONE}")
def local_codebook_hits(spark, sf):
    df, model = anchor(spark, sf, halves=1, k=8, local=True)
    return _single_hits(en.encode(df, model))


@query("signed_perm_encode", f"WITH {sql.codes('embeddings', K, M, KS, rotate=True)} SELECT id, c1, c2, fine FROM codes")
def signed_perm_encode(spark, sf):
    df, model = anchor(spark, sf, rotate=True)
    return en.encode(df, model)


@query("pair_encode", f"WITH {_C} SELECT id, c1, c2, fine FROM codes")
def pair_encode(spark, sf):
    df, model = anchor(spark, sf)
    return en.encode(df, model)


@query("multi_probe_encode", f"WITH {sql.codes('embeddings', K, M, KS, probes=3)} SELECT id, CAST(h AS INTEGER) AS half, CAST(rn AS INTEGER) AS rnk, CAST(c AS INTEGER) AS c, round(any_value(d), 6) AS d, list(CAST(j AS SMALLINT) ORDER BY b) AS fine FROM fc GROUP BY id, h, rn, c")
def multi_probe_encode(spark, sf):
    df, model = anchor(spark, sf)
    return en.encode_probes(df, model, 3).withColumn("d", F.round("d", 6))


def codes_of(spark, sf, view="embeddings", K=K, m=M, k=KS):
    df, model = anchor(spark, sf, view, K, m, k)
    return en.encode(df, model)


_ALL_HITS = f"WITH {_C} SELECT a, b, CAST(hits AS BIGINT) AS hits FROM (SELECT x.id AS a, y.id AS b, {sql.hits_pair('x', 'y', M)} AS hits FROM codes x JOIN codes y ON x.id < y.id) WHERE hits > 0"


@query("hits_all_pairs", _ALL_HITS)
def hits_all_pairs(spark, sf):
    return graph.pair_hits_naive(codes_of(spark, sf), M)


@query("hits_by_join", _ALL_HITS)
def hits_by_join(spark, sf):
    return graph.pair_hits(tk.flatten(codes_of(spark, sf)))


@query("pair_hits_salted", _ALL_HITS)
def pair_hits_salted(spark, sf):
    return graph.pair_hits(tk.flatten(codes_of(spark, sf)), salt=4)


@query("pair_hits_prefix", _ALL_HITS.replace("hits > 0", "hits >= 4"))
def pair_hits_prefix(spark, sf):
    return graph.pair_hits_prefix(tk.flatten(codes_of(spark, sf)), M, 4)


@query("flatten_tokens", f"WITH {_T} SELECT id, token FROM tokens")
def flatten_tokens(spark, sf):
    return tk.flatten(codes_of(spark, sf))


@query("cell_sizes", f"WITH {_C} SELECT c1, c2, count(*) AS n FROM codes GROUP BY 1, 2")
def cell_sizes(spark, sf):
    return search.cell_sizes(codes_of(spark, sf))


def split(spark, sf):
    """(model, queries, database codes): every tenth vector is a query."""
    df, model = anchor(spark, sf)
    return model, df.where(_QUERY), en.encode(df.where(f"NOT ({_QUERY})"), model)


_DB = _C + f",\ndb AS (SELECT * FROM codes WHERE NOT ({_QUERY}))"
_VIS = _DB + ",\n" + sql.visited(QUOTA, _QUERY)
_VIS_SQL = f"WITH {_VIS} SELECT qid, ord, c1, c2, round(d, 6) AS d, n, seen FROM vis"


@query("multi_sequence_cells", _VIS_SQL)
def multi_sequence_cells(spark, sf):
    model, q, db = split(spark, sf)
    return search.visited_cells(q, model, search.cell_sizes(db), QUOTA).withColumn("d", F.round("d", 6))


@query("quota_cells", _VIS_SQL)
def quota_cells(spark, sf):
    model, q, db = split(spark, sf)
    return search.visited_cells_relational(q, model, search.cell_sizes(db), QUOTA, 16).select("qid", "ord", "c1", "c2", F.round("d", 6).alias("d"), "n", "seen")


@query("quota_candidates", f"WITH {_VIS} SELECT qid, id FROM vis JOIN db USING (c1, c2)")
def quota_candidates(spark, sf):
    model, q, db = split(spark, sf)
    return search.candidates(search.visited_cells(q, model, search.cell_sizes(db), QUOTA), db).select("qid", "id")


_ALLP = sql.codes("embeddings", K, M, KS, probes=K) + f",\ndb AS (SELECT * FROM codes WHERE NOT ({_QUERY})),\n" + sql.visited(QUOTA, _QUERY)
_KNN = _ALLP + f""",
qh AS (SELECT id, h, c, list(CAST(j AS SMALLINT) ORDER BY b) AS f FROM fc WHERE {_QUERY} GROUP BY id, h, c),
sc AS (SELECT v.qid, db.id, WEIGHT + CASE WHEN TRUE THEN {sql.hits('list_concat(a.f, b.f)', 'db.fine', M)} END AS score FROM vis v JOIN qh a ON a.id = v.qid AND a.h = 0 AND a.c = v.c1 JOIN qh b ON b.id = v.qid AND b.h = 1 AND b.c = v.c2 JOIN db ON db.c1 = v.c1 AND db.c2 = v.c2),
knn AS (SELECT qid, id, score, CAST(row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS INTEGER) AS rnk FROM sc QUALIFY rnk <= {DEPTH})"""
_KNN_EXP, _KNN_NONE = _KNN.replace("WEIGHT", "exp(-v.d)"), _KNN.replace("WEIGHT", "0.0E0")
_KNN_OUT = " SELECT qid, id, round(CAST(score AS DOUBLE), 6) AS score, rnk FROM knn"


@query("knn_weighted", f"WITH {_KNN_EXP}{_KNN_OUT}")
def knn_weighted(spark, sf):
    model, q, db = split(spark, sf)
    return search.knn(q, model, db, DEPTH, QUOTA).withColumn("score", F.round("score", 6))


@query("knn_unweighted", f"WITH {_KNN_NONE}{_KNN_OUT}")
def knn_unweighted(spark, sf):
    model, q, db = split(spark, sf)
    return search.knn(q, model, db, DEPTH, QUOTA, weight="none").withColumn("score", F.round("score", 6))


# ---- query sets: by label on embeddings

_SETS = _T + f""",
qt AS (SELECT grp AS set_id, id AS qid, token FROM tokens WHERE id % 10 < 3),
dt AS (SELECT id, token FROM tokens WHERE id % 10 >= 3),
qs AS (SELECT set_id, qid, dt.id, CAST(count(*) AS DOUBLE) AS score FROM qt JOIN dt USING (token) GROUP BY 1, 2, 3)"""


def set_tokens(spark, sf, view="embeddings", K=K, m=M, k=KS):
    """(query tokens (set_id, qid, token), database tokens (id, token), all rows): sets are groups, 3 of 10 rows are queries."""
    df, model = anchor(spark, sf, view, K, m, k)
    t = tk.flatten(en.encode(df, model)).join(df.select("id", "grp"), "id")
    return t.where("id % 10 < 3").select(F.col("grp").alias("set_id"), F.col("id").alias("qid"), "token"), t.where("id % 10 >= 3").select("id", "token"), df


for _how, _agg in (("sum", "sum(score)"), ("max", "max(score)"), ("maxfreq", "max(score) * log2(1 + count(*))"), ("avg", "avg(score)")):
    query(f"pool_{_how}", f"WITH {_SETS} SELECT set_id, id, round({_agg}, 6) AS score FROM qs GROUP BY 1, 2")(lambda spark, sf, how=_how: querysets.pool(querysets.query_scores(*set_tokens(spark, sf)[:2]), how).withColumn("score", F.round("score", 6)))

_BATCH = f"WITH {_SETS} SELECT set_id, dt.id, count(*) AS score FROM qt JOIN dt USING (token) GROUP BY 1, 2"
query("batch_search", _BATCH)(lambda spark, sf: querysets.batch_search(*set_tokens(spark, sf)[:2], preaggregate=False))
query("batch_search_preagg", _BATCH)(lambda spark, sf: querysets.batch_search(*set_tokens(spark, sf)[:2]))


@query("batch_search_weighted", f"WITH {_SETS}, wq AS (SELECT set_id, token, CAST(sum(1 + qid % 3) AS BIGINT) AS k FROM qt GROUP BY 1, 2) SELECT set_id, dt.id, CAST(sum(k) AS BIGINT) AS score FROM wq JOIN dt USING (token) GROUP BY 1, 2")
def batch_search_weighted(spark, sf):
    """Each query of a set counts by a weight of its own."""
    q, db, _ = set_tokens(spark, sf)
    return querysets.batch_search(q.select("set_id", "token", (1 + F.col("qid") % 3).alias("w")), db)


@query("batch_search_top", f"WITH {_SETS} SELECT set_id, id, score, CAST(rnk AS INTEGER) AS rnk FROM (SELECT *, row_number() OVER (PARTITION BY set_id ORDER BY score DESC, id) AS rnk FROM (SELECT set_id, dt.id, count(*) AS score FROM qt JOIN dt USING (token) GROUP BY 1, 2)) WHERE rnk <= 25")
def batch_search_top(spark, sf):
    return querysets.batch_search(*set_tokens(spark, sf)[:2], top=25)


_PROBE = sql.codes("embeddings", K, M, KS, probes=2) + ",\n" + sql.tokens(M) + f""",
qt AS (SELECT v.grp AS set_id, (CAST(c AS BIGINT) << 32) | (CAST(pos AS BIGINT) << 16) | j AS token FROM fc JOIN v ON v.id = fc.id WHERE fc.id % 10 < 3),
dt AS (SELECT id, token FROM tokens WHERE id % 10 >= 3)"""


@query("batch_search_probes", f"WITH {_PROBE} SELECT set_id, dt.id, count(*) AS score FROM qt JOIN dt USING (token) GROUP BY 1, 2")
def batch_search_probes(spark, sf):
    df, model = anchor(spark, sf)
    near = en.encode_probes(df.where("id % 10 < 3"), model, 2).select("id", "half", "c", F.posexplode("fine").alias("b", "f"))
    token = F.shiftleft(F.col("c").cast("long"), 32).bitwiseOR(F.shiftleft((F.col("half") * (M // 2) + F.col("b")).cast("long"), 16)).bitwiseOR(F.col("f").cast("long"))
    q = near.join(df.select("id", F.col("grp").alias("set_id")), "id").select("set_id", token.alias("token"))
    return querysets.batch_search(q, tk.flatten(en.encode(df.where("id % 10 >= 3"), model)))


# ---- graph: on documents

_D = sql.codes("documents", DK, DM, DKS)
_DT = _D + ",\n" + sql.tokens(DM)
_DS = _DT + ",\n" + sql.pairs()
T_EDGE = 11


def doc_codes(spark, sf):
    return codes_of(spark, sf, "documents", DK, DM, DKS)


def doc_tokens(spark, sf):
    return tk.flatten(doc_codes(spark, sf))


def doc_pairs(spark, sf, least):
    """Over all tokens, however frequent."""
    return graph.pair_hits_blocks(materialize(doc_codes(spark, sf), "codes"), DM, least)


@query("token_stoplist", f"WITH {_DT}, {sql.stoplist(2, 200)} SELECT id, token FROM s_tokens")
def token_stoplist(spark, sf):
    return tk.stoplist(doc_tokens(spark, sf), 2, 200)


@query("token_stoplist_quantiles", f"WITH {_DT}, n AS (SELECT token, count(DISTINCT id) AS n FROM tokens GROUP BY 1), r AS (SELECT n, row_number() OVER (ORDER BY n) AS place, count(*) OVER () AS c FROM n), q AS (SELECT min(n) FILTER (WHERE place >= 0.25 * c) AS lo, min(n) FILTER (WHERE place >= 0.95 * c) AS hi FROM r) SELECT t.id, t.token FROM tokens t JOIN n USING (token) CROSS JOIN q WHERE n.n BETWEEN lo AND hi")
def token_stoplist_quantiles(spark, sf):
    """Bounds that are quantiles of the tokens' frequencies."""
    return tk.stoplist_quantiles(doc_tokens(spark, sf), 0.25, 0.95)


@query("token_fanout", f"WITH {_DT}, n AS (SELECT token, count(DISTINCT id) AS n FROM tokens GROUP BY 1) SELECT count(*) AS tokens, CAST(sum(n) AS BIGINT) AS rows, CAST(sum(n * (n - 1) // 2) AS BIGINT) AS pairs, max(n) AS largest FROM n")
def token_fanout(spark, sf):
    return tk.fanout(doc_tokens(spark, sf))


@query("pair_hits", f"WITH {_DS} SELECT a, b, hits FROM pairs WHERE hits >= 6")
def pair_hits(spark, sf):
    """Over all tokens, however frequent; six of 16 are too few for keys that tell pairs apart, so blocks of codes are compared."""
    return blocks.hit_pairs(doc_codes(spark, sf), DM, 6)


@query("edges_strict", f"WITH {_DS} SELECT a, b, hits FROM pairs WHERE hits > {T_EDGE}")
def edges_strict(spark, sf):
    return graph.edges(doc_pairs(spark, sf, T_EDGE + 1), T_EDGE)


@query("edges_loose", f"WITH {_DS} SELECT a, b, hits FROM pairs WHERE hits >= {T_EDGE}")
def edges_loose(spark, sf):
    return graph.edges(doc_pairs(spark, sf, T_EDGE), T_EDGE, strict=False)


_E = _DS + f",\nedges AS (SELECT a, b FROM pairs WHERE hits > {T_EDGE})"
_COMP = f"WITH RECURSIVE {_E}, {sql.components('edges')} SELECT id, component FROM comp"
for _m in ("star", "label", "local"):
    query("components" if _m == "star" else f"components_{_m}", _COMP)(lambda spark, sf, m=_m: graph.components(materialize(graph.links(materialize(doc_codes(spark, sf), "codes"), DM, T_EDGE), "edges"), method=m))

_NODES = f"WITH RECURSIVE {_E}, {sql.components('edges', 'SELECT id FROM codes')}"


def clustered(spark, sf):
    return graph.cluster_all(doc_codes(spark, sf), DM, T_EDGE)


query("cluster_documents", f"{_NODES} SELECT id, component FROM comp")(clustered)
_BANDS = f"{_NODES}, z AS (SELECT component, count(*) AS n FROM comp GROUP BY 1) SELECT CAST(CASE WHEN n >= 10 THEN 10 WHEN n >= 5 THEN 5 WHEN n >= 2 THEN 2 ELSE 1 END AS INTEGER) AS band, count(*) AS components, CAST(sum(n) AS BIGINT) AS items FROM z GROUP BY 1"
query("cluster_size_bands", _BANDS)(lambda spark, sf: metrics.graph_stats(clustered(spark, sf), (1, 2, 5, 10)))
query("noisy_labels", f"{_NODES} SELECT id, component AS pseudo_label FROM comp WHERE component IN (SELECT component FROM comp GROUP BY 1 HAVING count(*) BETWEEN 3 AND 50)")(lambda spark, sf: graph.noisy_labels(clustered(spark, sf), 3, 50))

# ---- preparation and cost measures

_VAR = f"v AS ({sql.vec('embeddings')}), x AS (SELECT id, i, vec[i] AS x FROM v CROSS JOIN (SELECT unnest(range(1, 65)) AS i))"


@query("covariance_upper", f"WITH {_VAR} SELECT CAST(a.i - 1 AS INTEGER) AS i, CAST(b.i - 1 AS INTEGER) AS j, round(covar_pop(a.x, b.x), 6) AS cov FROM x a JOIN x b ON a.id = b.id AND a.i <= b.i GROUP BY 1, 2")
def covariance_upper(spark, sf):
    _, _, cov = prep.covariance(emb(spark, sf))
    d = len(cov)
    return spark.createDataFrame([(i, j, float(np.round(cov[i, j], 6)) + 0.0) for i in range(d) for j in range(i, d)], "i int, j int, cov double")


@query("dim_variance_balance", f"WITH {_VAR}, s AS (SELECT i, var_pop(x) AS s FROM x GROUP BY 1), r AS (SELECT i, row_number() OVER (ORDER BY s DESC, i) - 1 AS r FROM s) SELECT CAST(i - 1 AS INTEGER) AS dim, CAST(CASE WHEN r % 4 IN (0, 3) THEN 0 ELSE 1 END AS INTEGER) AS half FROM r")
def dim_variance_balance(spark, sf):
    _, _, cov = prep.covariance(emb(spark, sf))
    perm = prep.snake(np.diag(cov))
    h = len(perm) // 2
    return spark.createDataFrame([(int(i), int(p >= h)) for p, i in enumerate(perm)], "dim int, half int")


@query("probe_stats", f"WITH {_VIS}, p AS (SELECT qid, count(*) AS w, sum(n) AS t FROM vis GROUP BY 1) SELECT count(*) AS queries, round(avg(w), 6) AS mean_cells, round(avg(t), 6) AS mean_candidates, max(w) AS most_cells FROM p")
def probe_stats(spark, sf):
    return metrics.probe_stats(multi_sequence_cells(spark, sf))


@query("code_bytes", f"SELECT * FROM (VALUES ('fine_bytes', {M} * log2({KS}) / 8), ('coarse_bits', 2 * log2({K}))) t(name, value)")
def code_bytes(spark, sf):
    _, model = anchor(spark, sf)
    return spark.createDataFrame([(k, float(v)) for k, v in metrics.code_bytes(model).items()], "name string, value double")


# ---- accuracy

_BRUTE = f"""bq AS (SELECT id, vec FROM ({sql.vec('embeddings')}) WHERE {_QUERY}), bd AS (SELECT id, vec FROM ({sql.vec('embeddings')}) WHERE NOT ({_QUERY})),
brute AS (SELECT bq.id AS qid, bd.id, {sql.square('bq.vec', 'bd.vec', 64)} AS d FROM bq CROSS JOIN bd),
near AS (SELECT qid, id, d, CAST(row_number() OVER (PARTITION BY qid ORDER BY d, id) AS INTEGER) AS rnk FROM brute)"""
RECALL_SQL = "SELECT CAST(r AS INTEGER) AS R, round(avg(CASE WHEN k.rnk <= r THEN 1.0 ELSE 0.0 END), 6) AS recall FROM near t CROSS JOIN (SELECT unnest([1, 5, 10, 20]) AS r) LEFT JOIN {0} k ON k.qid = t.qid AND k.id = t.id WHERE t.rnk = 1 GROUP BY r"
DEPTHS = [1, 5, 10, 20]


def truth(spark, sf):
    from codematch.operators.baselines import brute

    df = emb(spark, sf)
    return brute.knn(df.where(_QUERY), df.where(f"NOT ({_QUERY})"), 1).select("qid", "id")


@query("brute_knn", f"WITH {_BRUTE} SELECT qid, id, round(d, 6) AS score, rnk FROM near WHERE rnk <= 10")
def brute_knn(spark, sf):
    from codematch.operators.baselines import brute

    df = emb(spark, sf)
    return brute.knn(df.where(_QUERY), df.where(f"NOT ({_QUERY})"), 10).withColumn("score", F.round("score", 6))


@query("recall_ranking", f"WITH {_KNN_EXP}, {_BRUTE} {RECALL_SQL.format('knn')}")
def recall_ranking(spark, sf):
    model, q, db = split(spark, sf)
    return metrics.recall_at(search.knn(q, model, db, DEPTH, QUOTA), truth(spark, sf), DEPTHS)


@query("recall_retrieval", " UNION ALL ".join(f"SELECT CAST({t} AS INTEGER) AS quota, * FROM (WITH {_DB}, {sql.visited(t, _QUERY)}, {_BRUTE}, got AS (SELECT qid, db.id FROM vis JOIN db USING (c1, c2)) SELECT round(avg(CASE WHEN g.id IS NULL THEN 0.0 ELSE 1.0 END), 6) AS recall, round((SELECT count(*) FROM got) * 1.0 / count(*), 6) AS mean_candidates FROM near t LEFT JOIN got g ON g.qid = t.qid AND g.id = t.id WHERE t.rnk = 1)" for t in (25, 50, 100)))
def recall_retrieval(spark, sf):
    model, q, db = split(spark, sf)
    sizes, real = search.cell_sizes(db), truth(spark, sf)
    out = None
    for t in (25, 50, 100):
        got = search.candidates(search.visited_cells(q, model, sizes, t), db).select("qid", "id").withColumn("hit", F.lit(1.0))
        total = got.agg(F.count(F.lit(1)).alias("n"))
        one = real.join(got, ["qid", "id"], "left").agg(F.avg(F.coalesce("hit", F.lit(0.0))).alias("r"), F.count(F.lit(1)).alias("q")).crossJoin(total)
        one = one.select(F.lit(t).alias("quota"), F.round("r", 6).alias("recall"), F.round(F.col("n") / F.col("q"), 6).alias("mean_candidates"))
        out = one if out is None else out.unionAll(one)
    return out


@query("rank_agreement", f"WITH {_KNN_EXP}, j AS (SELECT s.qid, percent_rank() OVER (PARTITION BY s.qid ORDER BY s.score) AS x, percent_rank() OVER (PARTITION BY s.qid ORDER BY b.d) AS y FROM (SELECT qid, id, round(score, 6) AS score FROM sc) s JOIN (SELECT bq.id AS qid, bd.id, round({sql.square('bq.vec', 'bd.vec', 64)}, 6) AS d FROM (SELECT id, vec FROM v WHERE {_QUERY}) bq CROSS JOIN (SELECT id, vec FROM v WHERE NOT ({_QUERY})) bd) b ON b.qid = s.qid AND b.id = s.id) SELECT qid, round(corr(x, y), 6) AS corr FROM j GROUP BY 1")
def rank_agreement(spark, sf):
    model, q, db = split(spark, sf)
    df = emb(spark, sf)
    got = materialize(search.knn(q, model, db, 10**9, QUOTA).select("qid", "id", F.round("score", 6).alias("score")), "candidates")
    side = lambda name, key: df.select(F.col("id").alias(key), F.col("vec").alias(name))
    both = got.join(side("x", "qid"), "qid").join(side("y", "id"), "id")
    d = F.aggregate(F.zip_with("x", "y", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda a, b: a + b)
    return metrics.rank_corr(both.select("qid", "id", "score", F.round(d, 6).alias("d")))
