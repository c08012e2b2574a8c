"""The experiments on the given tables: which method wins, and how measures move with parameters."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from codematch.operators import blocks, encode as en, grams, graph, metrics, querysets, score, search, tokens as tk, train, vectors
from codematch.operators.baselines import binary, brute, hashes, rawdist, tags
from codematch.operators.model import anchor
from codematch.plans import sql
from codematch.plans.methods import _ALLP, _BRUTE, _D, _DB, _DS, _DT, _KNN_EXP, _QUERY, DEPTH, DEPTHS, DK, DKS, DM, K, KS, M, QUOTA, RECALL_SQL, Q as METHODS, SQL as METHOD_SQL, codes_of, doc_codes, doc_tokens, emb, split, truth
from codematch.sources.io import materialize, read_table

Q: dict = {}
SQL: dict[str, str] = {}
BITS = 64


def query(name, text=None):
    def add(f):
        Q[name] = f
        if text is not None:
            SQL[name] = text
        return f

    return add


# ---- nearest neighbours: codes against binary codes at the same number of bits

RADII = [12, 16, 20, 24, 28]
RANKS = [1, 10, 50, 100]


def lsh_sql(view: str, bits: int) -> str:
    """CTE bt(id, b, bit): signs of projections on planes of +1 and -1."""
    return f"""v AS ({sql.vec(view)}),
pl AS (SELECT b, i, CASE WHEN CAST('0x' || right(md5('0:' || b || ':' || i), 1) AS INTEGER) % 2 = 0 THEN 1.0 ELSE -1.0 END AS s FROM (SELECT unnest(range({bits})) AS b) CROSS JOIN (SELECT unnest(range(64)) AS i)),
pw AS (SELECT b, list(s ORDER BY i) AS w FROM pl GROUP BY b),
bt AS (SELECT id, b, CAST(list_sum([vec[i] * w[i] for i in range(1, 65)]) >= 0 AS BIGINT) AS bit FROM v CROSS JOIN pw)"""


def distance_sql(bits: int) -> str:
    return " + ".join(f"bit_count(xor(a.words[{i}], b.words[{i}]))" for i in range(1, -(-bits // 32) + 1))


_LSH = lsh_sql("embeddings", BITS)
_MEAN = f"""v AS ({sql.vec('embeddings')}), mu AS (SELECT i, avg(vec[i]) AS mu FROM v CROSS JOIN (SELECT unnest(range(1, 65)) AS i) GROUP BY i),
bt AS (SELECT id, i - 1 AS b, CAST(vec[i] > mu AS BIGINT) AS bit FROM v CROSS JOIN mu)"""
_WORDS = ", ws AS (SELECT id, b // 32 AS w, CAST(sum(bit << (b % 32)) AS BIGINT) AS x FROM bt GROUP BY 1, 2), codes AS (SELECT id, list(x ORDER BY w) AS words FROM ws GROUP BY id)"
_DIST = distance_sql(BITS)
_RADIUS = f""", hd AS (SELECT a.id AS qid, b.id, {_DIST} AS d FROM codes a JOIN codes b ON a.id % 10 = 0 AND b.id % 10 <> 0), {_BRUTE}
SELECT CAST(r AS INTEGER) AS radius, round(count(*) FILTER (WHERE d <= r) * 1.0 / count(DISTINCT hd.qid), 6) AS mean_found, round(count(*) FILTER (WHERE d <= r AND t.id IS NOT NULL) * 1.0 / count(DISTINCT hd.qid), 6) AS recall
FROM hd LEFT JOIN (SELECT qid, id FROM near WHERE rnk = 1) t ON t.qid = hd.qid AND t.id = hd.id CROSS JOIN (SELECT unnest({RADII}) AS r) GROUP BY r"""
_RANKED = f""", hd AS (SELECT a.id AS qid, b.id, {_DIST} AS d FROM codes a JOIN codes b ON a.id % 10 = 0 AND b.id % 10 <> 0),
rk AS (SELECT qid, id, row_number() OVER (PARTITION BY qid ORDER BY d, id) AS rnk FROM hd), {_BRUTE}
{RECALL_SQL.format('rk').replace('[1, 5, 10, 20]', str(RANKS))}"""


def lsh_codes(spark, sf):
    return coded(emb(spark, sf), hashes.lsh(64, BITS))


def coded(df, made):
    d, _, bits_of = made
    return binary.encode(df, d, bits_of)


MAKERS = {
    "lsh": lambda df: hashes.lsh(64, BITS),
    "pcae": lambda df: hashes.pca_signs(df, BITS),
    "itq": lambda df: hashes.itq(df, BITS),
    "usplh": lambda df: hashes.sequential(df, BITS),
    "spectral": lambda df: hashes.spectral(df, BITS),
}
query("lsh_codes", f"WITH {_LSH}{_WORDS} SELECT id, words FROM codes")(lsh_codes)


@query("centred_sign_codes", f"WITH {_MEAN}{_WORDS} SELECT id, words FROM codes")
def centred_sign_codes(spark, sf):
    """Signs of the centred dimensions as they are, without principal axes."""
    return coded(emb(spark, sf), hashes.pca_signs(emb(spark, sf), BITS, rotate=False))


@query("lsh_hamming_knn", f"WITH {_LSH}{_WORDS}, s AS (SELECT a.id AS qid, b.id, CAST({_DIST} AS DOUBLE) AS score FROM codes a JOIN codes b ON a.id % 10 = 0 AND b.id % 10 <> 0) SELECT qid, id, score, CAST(rnk AS INTEGER) AS rnk FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score, id) AS rnk FROM s) WHERE rnk <= 10")
def lsh_hamming_knn(spark, sf):
    c = lsh_codes(spark, sf)
    return binary.hamming_knn(c.where(_QUERY), c.where(f"NOT ({_QUERY})"), 10, 2)


@query("lsh_banded", f"WITH {_LSH}, bd AS (SELECT id, b // 16 AS band, sum(bit << (b % 16)) AS x FROM bt GROUP BY 1, 2) SELECT DISTINCT p.id AS a, q.id AS b FROM bd p JOIN bd q USING (band, x) WHERE p.id < q.id")
def lsh_banded(spark, sf):
    return binary.banded_pairs(lsh_codes(spark, sf), BITS, 4)


@query("centred_sign_pairs", f"WITH {_MEAN}{_WORDS} SELECT a.id AS a, b.id AS b, CAST({_DIST} AS INTEGER) AS dist FROM codes a JOIN codes b ON a.id < b.id WHERE {_DIST} <= 18")
def centred_sign_pairs(spark, sf):
    return blocks.near_bits(centred_sign_codes(spark, sf), 18, BITS)


def ranked_recall(made):
    """Recall of a ranking by Hamming distance over all rows."""

    def run(spark, sf):
        df = emb(spark, sf)
        c = materialize(coded(df, made(df)), "bits")
        return metrics.recall_at(binary.hamming_knn(c.where(_QUERY), c.where(f"NOT ({_QUERY})"), max(RANKS), 2), truth(spark, sf), RANKS)

    return run


def radius_recall(made):
    def run(spark, sf):
        df = emb(spark, sf)
        c = coded(df, made(df))
        return binary.recall_by_radius(c.where(_QUERY), c.where(f"NOT ({_QUERY})"), truth(spark, sf), RADII, 2)

    return run


for _name, _made in MAKERS.items():
    query(f"ann_recall_{_name}", f"WITH {_LSH}{_WORDS}{_RADIUS}" if _name == "lsh" else None)(radius_recall(_made))
    query(f"ann_rank_{_name}", f"WITH {_LSH}{_WORDS}{_RANKED}" if _name == "lsh" else None)(ranked_recall(_made))
query("ann_recall_centred_sign", f"WITH {_MEAN}{_WORDS}{_RADIUS}")(radius_recall(lambda df: hashes.pca_signs(df, BITS, rotate=False)))
for _name, _key in (("pcae", "pcae_codes"), ("itq", "itq_codes"), ("usplh", "seqproj_codes"), ("spectral", "spectral_codes")):
    query(_key)(lambda spark, sf, made=MAKERS[_name]: coded(emb(spark, sf), made(emb(spark, sf))))
query("pca_rotation_encode")(lambda spark, sf: en.encode(emb(spark, sf), train.fit(emb(spark, sf), 4, M, KS, iters=4)))
query("pca_reduced_encode")(lambda spark, sf: en.encode(emb(spark, sf), train.fit(emb(spark, sf), 4, M, KS, pca=32, iters=4)))

#: Positions and values of trained codes with as many bits as the binary codes have, and clusters of each half.
EVEN_M, EVEN_K, EVEN_COARSE = 16, 16, 4
#: Quotas of candidates.
QUOTAS = [25, 50, 100, 200, 300]


def trained_split(spark, sf):
    """A trained, variance-balanced model whose fine codes have BITS bits, queries, and the codes of the rest."""
    df = emb(spark, sf)
    model = train.fit(df, EVEN_COARSE, EVEN_M, EVEN_K, iters=8)
    return model, df.where(_QUERY), materialize(en.encode(df.where(f"NOT ({_QUERY})"), model), "codes")


@query("ann_recall_trained")
def ann_recall_trained(spark, sf):
    """Ranking by hits with a trained model, all cells visited."""
    model, q, db = trained_split(spark, sf)
    return metrics.recall_at(search.knn(q, model, db, max(RANKS), 10**9), truth(spark, sf), RANKS)


@query("ann_distance_trained")
def ann_distance_trained(spark, sf):
    """The same ranked by quantized distance."""
    model, q, db = trained_split(spark, sf)
    return metrics.recall_at(rawdist.knn(q, model, db, max(RANKS), 10**9), truth(spark, sf), RANKS)


@query("ann_retrieval_trained")
def ann_retrieval_trained(spark, sf):
    """Unordered retrieval with the trained model: recall and candidates by quota, to hold against the binary codes' radii."""
    model, q, db = trained_split(spark, sf)
    sizes, real = search.cell_sizes(db), materialize(truth(spark, sf), "truth")
    out = None
    for quota in QUOTAS:
        got = search.candidates(search.visited_cells(q, model, sizes, quota), db).select("qid", "id").join(real.withColumn("hit", F.lit(1)), ["qid", "id"], "left")
        one = got.agg(F.countDistinct("qid").alias("q"), F.count(F.lit(1)).alias("n"), F.count("hit").alias("k"))
        one = one.select(F.lit(quota).alias("quota"), F.round(F.col("n") / F.col("q"), 6).alias("mean_found"), F.round(F.col("k") / F.col("q"), 6).alias("recall"))
        out = one if out is None else out.unionAll(one)
    return out


_ADC = _ALLP + f""",
bp AS (SELECT id, h, c, b, part FROM bk WHERE {_QUERY}),
rawd AS (SELECT v.qid, db.id, sum({sql.square('@P@', 's.sp', 8)}) AS score FROM vis v JOIN db ON db.c1 = v.c1 AND db.c2 = v.c2 JOIN bp ON bp.id = v.qid AND bp.c = CASE WHEN bp.h = 0 THEN v.c1 ELSE v.c2 END JOIN sb s ON s.h = bp.h AND s.b = bp.b AND s.j = db.fine[bp.h * {M // 2} + bp.b + 1] @X@ GROUP BY 1, 2),
knn AS (SELECT qid, id, score, row_number() OVER (PARTITION BY qid ORDER BY score, id) AS rnk FROM rawd), {_BRUTE}
{RECALL_SQL.format('knn')}"""


def _distance(symmetric):
    def run(spark, sf):
        model, q, db = split(spark, sf)
        return metrics.recall_at(rawdist.knn(q, model, db, DEPTH, QUOTA, symmetric), truth(spark, sf), DEPTHS)

    return run


query("ann_adc", f"WITH {_ADC.replace('@P@', 'bp.part').replace('@X@', '')}")(_distance(False))
query("ann_sdc", f"WITH {_ADC.replace('@P@', 'u.sp').replace('@X@', 'JOIN fc g ON g.id = bp.id AND g.h = bp.h AND g.c = bp.c AND g.b = bp.b JOIN sb u ON u.h = bp.h AND u.b = bp.b AND u.j = g.j')}")(_distance(True))


def coarse_adc(halves):
    """Coarse clusters and residual codes without rotation, ranked by distance: recall at 1, 10, 50 and 100 of all rows."""

    def run(spark, sf):
        df = emb(spark, sf)
        model = train.fit(df, EVEN_COARSE, EVEN_M, EVEN_K, halves=halves, rotation="none", balanced=False, iters=6)
        q, db = df.where(_QUERY), en.encode(df.where(f"NOT ({_QUERY})"), model)
        return metrics.recall_at(rawdist.knn(q, model, db, max(RANKS), 10**9), truth(spark, sf), RANKS)

    return run


query("ivf_adc")(coarse_adc(1))
query("multi_index_adc")(coarse_adc(2))
_ONE_ADC = f"""{sql.codes("embeddings", K, M, KS, halves=1, probes=K)}, db AS (SELECT * FROM codes WHERE NOT ({_QUERY})),
dq AS (SELECT bk.id AS qid, bk.c AS c1, bk.b, bk.part FROM bk WHERE {_QUERY}),
rawd AS (SELECT dq.qid, db.id, sum({sql.square('dq.part', 's.sp', 64 // M)}) AS score FROM dq JOIN db ON db.c1 = dq.c1 JOIN sb s ON s.h = 0 AND s.b = dq.b AND s.j = db.fine[dq.b + 1] GROUP BY 1, 2),
knn AS (SELECT qid, id, score, row_number() OVER (PARTITION BY qid ORDER BY score, id) AS rnk FROM rawd), {_BRUTE}
{RECALL_SQL.format('knn')}"""


@query("ivf_adc_anchor", f"WITH {_ONE_ADC}")
def ivf_adc_anchor(spark, sf):
    """One coarse space with the model that needs no training, all clusters visited."""
    df = emb(spark, sf)
    model = anchor(df, K, M, KS, halves=1)
    q, db = df.where(_QUERY), en.encode(df.where(f"NOT ({_QUERY})"), model)
    return metrics.recall_at(rawdist.knn(q, model, db, DEPTH, 10**9), truth(spark, sf), DEPTHS)


@query("pq_scan_recall")
def pq_scan_recall(spark, sf):
    df = emb(spark, sf)
    model = train.fit_pq(df, M, KS, 6)
    return metrics.recall_at(rawdist.pq_scan(df.where(_QUERY), df.where(f"NOT ({_QUERY})"), model, 100), truth(spark, sf), [1, 10, 50, 100])


@query("random_floor", f"WITH s AS (SELECT a.vec_id AS qid, b.vec_id AS id, CAST(CAST('0x' || left(md5('0:' || a.vec_id || ':' || b.vec_id), 8) AS BIGINT) AS DOUBLE) AS score FROM embeddings a JOIN embeddings b ON a.vec_id % 10 = 0 AND b.vec_id % 10 <> 0) SELECT qid, id, score, CAST(rnk AS INTEGER) AS rnk FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score, id) AS rnk FROM s) WHERE rnk <= 10")
def random_floor(spark, sf):
    df = emb(spark, sf)
    return brute.random_rank(df.where(_QUERY), df.where(f"NOT ({_QUERY})"), 10)


query("reference_clusters")(lambda spark, sf: brute.kmeans_clusters(vectors.documents(spark, sf), 8))
query("reference_clusters_bisecting")(lambda spark, sf: brute.kmeans_clusters(vectors.documents(spark, sf), 8, kind="bisecting"))


@query("distortion_by_variant")
def distortion_by_variant(spark, sf):
    """Mean squared error of each variant of the model."""
    df = emb(spark, sf)
    out = None
    for name, how in {"pq": None, "two halves, no rotation": {"rotation": "none", "balanced": False}, "two halves, balanced": {"rotation": "none"}, "two halves, random rotation": {"rotation": "random"}, "two halves, local rotation": {}, "one space, local rotation": {"halves": 1}, "local codebooks": {"codebooks": "local"}}.items():
        model = train.fit_pq(df, M, KS, 5) if how is None else train.fit(df, 4, M, KS, iters=5, **how)
        one = metrics.distortion(df, model).select(F.lit(name).alias("variant"), "n", F.round("mean", 6).alias("mean"))
        out = one if out is None else out.unionAll(one)
    return out


# ---- query sets

PS = [10, 50, 100, 200, 300, 400, 500]


def _expand_sql(ctes: str) -> str:
    return f"""WITH {ctes}, tk AS (SELECT t.*, CAST('0x' || left(md5(CAST(id AS VARCHAR)), 8) AS BIGINT) % 10 AS u FROM tokens t),
qt AS (SELECT grp AS set_id, token FROM tk WHERE u < 3), dt AS (SELECT id, token FROM tk WHERE u >= 3),
res AS (SELECT set_id, id, row_number() OVER (PARTITION BY set_id ORDER BY score DESC, id) AS rnk FROM (SELECT set_id, dt.id, count(*) AS score FROM qt JOIN dt USING (token) GROUP BY 1, 2))
SELECT set_id, CAST(p AS INTEGER) AS P, round(avg(CASE WHEN c.grp = r.set_id THEN 1.0 ELSE 0.0 END), 6) AS precision FROM res r JOIN codes c USING (id) CROSS JOIN (SELECT unnest({PS}) AS p) WHERE rnk <= p GROUP BY 1, 2"""


def expand(view, k1, m, ks):
    def run(spark, sf):
        df = vectors.VIEWS[view](spark, sf)
        model = anchor(df, k1, m, ks)
        t = tk.flatten(en.encode(df, model)).join(df.select("id", "grp"), "id").withColumn("u", F.conv(F.substring(F.md5(F.col("id").cast("string")), 1, 8), 16, 10).cast("long") % 10)
        got = querysets.batch_search(t.where("u < 3").select(F.col("grp").alias("set_id"), "token"), t.where("u >= 3"), top=max(PS))
        return metrics.precision_at(got, df.select(F.col("grp").alias("set_id"), "id"), PS)

    return run


query("group_expand_lang", _expand_sql(_DT))(expand("documents", DK, DM, DKS))
query("group_expand_label", _expand_sql(sql.codes("embeddings", K, M, KS) + ",\n" + sql.tokens(M)))(expand("embeddings", K, M, KS))


def _pool_precision(how):
    agg = {"sum": "sum(score)", "max": "max(score)", "maxfreq": "max(score) * log2(1 + count(*))"}[how]

    def run(spark, sf):
        df = vectors.documents(spark, sf)
        df = materialize(df, "vectors")
        codes = materialize(en.encode(df, anchor(df, DK, DM, DKS)).join(df.select("id", "grp"), "id"), "codes")
        q, db = codes.where("id % 10 < 3"), codes.where("id % 10 >= 3")
        if how == "sum":
            got = querysets.batch_search(tk.flatten(q, ("grp",)).withColumnRenamed("grp", "set_id"), tk.flatten(db), top=max(PS))
        else:
            best = blocks.pooled_hits(q.withColumnRenamed("grp", "set_id"), db, DM)
            score_ = F.col("most") * (F.log2(1 + F.col("reached").cast("double")) if how == "maxfreq" else F.lit(1))
            got = search.top(best.select("set_id", "id", score_.cast("double").alias("score")), max(PS), "set_id")
        return metrics.precision_at(got, df.select(F.col("grp").alias("set_id"), "id"), PS)

    return run, f"""WITH {_DT}, qs AS (SELECT q.grp AS set_id, q.id AS qid, d.id, CAST(count(*) AS DOUBLE) AS score FROM tokens q JOIN tokens d ON q.token = d.token AND q.id % 10 < 3 AND d.id % 10 >= 3 GROUP BY 1, 2, 3),
res AS (SELECT set_id, id, row_number() OVER (PARTITION BY set_id ORDER BY score DESC, id) AS rnk FROM (SELECT set_id, id, {agg} AS score FROM qs GROUP BY 1, 2))
SELECT set_id, CAST(p AS INTEGER) AS P, round(avg(CASE WHEN c.grp = r.set_id THEN 1.0 ELSE 0.0 END), 6) AS precision FROM res r JOIN codes c USING (id) CROSS JOIN (SELECT unnest({PS}) AS p) WHERE rnk <= p GROUP BY 1, 2"""


for _how in ("sum", "max", "maxfreq"):
    _run, _text = _pool_precision(_how)
    query(f"pool_{_how}_precision", _text)(_run)

TAGS = {"en": ["the", "and", "of"], "de": ["der", "und", "die"], "fr": ["le", "et", "les"], "es": ["el", "que", "los"]}
_TAG = " UNION ALL ".join(
    f"SELECT '{g}' AS set_id, doc_id AS id, score, CAST(row_number() OVER (ORDER BY score DESC, doc_id) AS INTEGER) AS rnk FROM (SELECT doc_id, {' + '.join(f'len([x for x in w if x = {t!r}])' for t in ts)} AS score FROM (SELECT doc_id, string_split_regex(lower(text), '[^\\p{{L}}\\p{{N}}]+') AS w FROM documents) WHERE {' AND '.join(f'list_contains(w, {t!r})' for t in ts)} ORDER BY score DESC, doc_id LIMIT 50)"
    for g, ts in TAGS.items()
)


def tag_search(spark, sf):
    docs, out = read_table(spark, sf, "documents").select(F.col("doc_id").alias("id"), "text"), None
    for g, terms in TAGS.items():
        one = tags.search(docs, terms, 50).withColumn("set_id", F.lit(g))
        out = one if out is None else out.unionByName(one)
    return out


query("tag_search", _TAG)(tag_search)
query("tag_search_baseline", f"SELECT t.set_id, CAST(p AS INTEGER) AS P, round(avg(CASE WHEN d.lang = t.set_id THEN 1.0 ELSE 0.0 END), 6) AS precision FROM ({_TAG}) t JOIN documents d ON d.doc_id = t.id CROSS JOIN (SELECT unnest([10, 50]) AS p) WHERE rnk <= p GROUP BY 1, 2")(
    lambda spark, sf: metrics.precision_at(tag_search(spark, sf), read_table(spark, sf, "documents").select(F.col("lang").alias("set_id"), F.col("doc_id").alias("id")), [10, 50])
)


# ---- duplicates: pair precision and recall against word-3-gram Jaccard of 0.7

_GRAMS = r"""gw AS (SELECT doc_id AS id, [x for x in string_split_regex(lower(text), '[^\p{L}\p{N}]+') if x <> ''] AS w FROM documents),
gs AS (SELECT DISTINCT id, array_to_string(w[i:i+2], ' ') AS g FROM (SELECT id, w, unnest(range(1, len(w) - 1)) AS i FROM gw)),
gn AS (SELECT id, count(*) AS n FROM gs GROUP BY 1),
truth AS (SELECT a, b FROM (SELECT x.id AS a, y.id AS b, count(*) AS c FROM gs x JOIN gs y ON x.g = y.g AND x.id < y.id GROUP BY 1, 2) JOIN gn p ON p.id = a JOIN gn q ON q.id = b WHERE c * 10 >= 7 * (p.n + q.n - c))"""


def _texts(spark, sf):
    return read_table(spark, sf, "documents").select(F.col("doc_id").alias("id"), "text")


def duplicate_truth(spark, sf):
    """(a, b) of documents with word-3-gram Jaccard similarity of 0.7 or more."""
    members, pairs = grams.near_classes(_texts(spark, sf))
    one, two = (members.select(F.col("class").alias(c), F.col("id").alias(f"id{c}")) for c in "ab")
    met = pairs.join(one, "a").join(two, "b").select("ida", "idb")
    same = members.select("class", F.col("id").alias("ida")).join(members.select("class", F.col("id").alias("idb")), "class").where("ida < idb")
    return met.unionAll(same.select("ida", "idb")).select(F.least("ida", "idb").alias("a"), F.greatest("ida", "idb").alias("b")).distinct()


def _pr_sql(ctes: str, pairs: str, steps: list[int], sign: str) -> str:
    return f"""WITH {ctes}, {_GRAMS}, pr AS ({pairs}), pos AS (SELECT count(*) AS k FROM truth)
SELECT threshold, found, correct, round(correct * 1.0 / nullif(found, 0), 6) AS precision, round(correct * 1.0 / nullif(k, 0), 6) AS recall FROM (
SELECT CAST(t AS INTEGER) AS threshold, count(*) FILTER (WHERE s {sign} t) AS found, count(*) FILTER (WHERE s {sign} t AND tr.a IS NOT NULL) AS correct FROM pr LEFT JOIN truth tr ON tr.a = pr.a AND tr.b = pr.b CROSS JOIN (SELECT unnest({steps}) AS t) GROUP BY t) CROSS JOIN pos"""


STEPS, DISTANCES = [5, 7, 9, 11, 13, 16], [0, 2, 4, 6, 8, 12, 16]
#: Bits of the random projections that duplicates are sought with.
WIDE = 128


@query("dedup_pr_ccm", _pr_sql(_DT + ", " + sql.pairs(), "SELECT a, b, hits AS s FROM pairs", STEPS, ">="))
def dedup_pr_ccm(spark, sf):
    return _code_pr(spark, sf, codes_of(spark, sf, "documents", DK, DM, DKS))


def _truth_counts(spark, sf, codes, columns, s):
    """(s, n): how many true pairs have s of the codes of both, null where one has no code.

    Documents with the same grams and the same code are one row with their number, so copies make no pairs.
    """
    members, pairs = grams.near_classes(_texts(spark, sf))
    coded_ = members.join(codes.select("id", F.struct(*columns).alias("code")), "id", "left")
    kinds = materialize(coded_.groupBy("class", "code").agg(F.countDistinct("id").alias("n")), "kinds")
    side = lambda x: kinds.select(F.col("class").alias(x), F.col("code").alias(f"{x}_"), F.col("n").alias(f"n{x}"))
    apart = pairs.join(side("a"), "a").join(side("b"), "b")
    number = F.row_number().over(Window.partitionBy("class").orderBy("code"))
    own = kinds.withColumn("k", number)
    mixed = own.select("class", F.col("k").alias("ka"), F.col("code").alias("a_"), F.col("n").alias("na")).join(own.select("class", F.col("k").alias("kb"), F.col("code").alias("b_"), F.col("n").alias("nb")), "class").where("ka < kb")
    same = kinds.where("n > 1").select(F.col("code").alias("a_"), F.col("code").alias("b_"), F.expr("n * (n - 1) DIV 2").alias("n"))
    met = apart.select("a_", "b_", F.expr("na * nb").alias("n")).unionAll(mixed.select("a_", "b_", F.expr("na * nb").alias("n"))).unionAll(same)
    return met.select(s.cast("long").alias("s"), "n").groupBy("s").agg(F.sum("n").alias("n"))


def _code_pr(spark, sf, codes):
    """Found pairs are counted and true ones are scored; no pair of the former is written."""
    codes = materialize(codes, "codes")
    truth = _truth_counts(spark, sf, codes, ["c1", "c2", "fine"], score.hits_pair("a_", "b_", DM))
    return metrics.pair_pr_counted(blocks.count_hits(codes, DM, min(STEPS)), truth, STEPS)


def _bit_pr(made, bits):
    def run(spark, sf):
        df = vectors.documents(spark, sf)
        codes = materialize(coded(df, made(df)), "bits")
        apart = binary.hamming(F.col("a_.words"), F.col("b_.words"), -(-bits // binary.WORD))
        truth = _truth_counts(spark, sf, codes, ["words"], apart)
        return metrics.pair_pr_counted(blocks.count_distances(codes, max(DISTANCES), bits), truth, DISTANCES, rising=False)

    return run


def _bit_pairs(bits):
    return f"SELECT a.id AS a, b.id AS b, {distance_sql(bits)} AS s FROM codes a JOIN codes b ON a.id < b.id WHERE {distance_sql(bits)} <= {max(DISTANCES)}"


query("dedup_pr_lsh", _pr_sql(lsh_sql("documents", WIDE) + _WORDS, _bit_pairs(WIDE), DISTANCES, "<="))(_bit_pr(lambda df: hashes.lsh(64, WIDE), WIDE))
query("dedup_pr_centred_sign", _pr_sql(_MEAN.replace(sql.vec("embeddings"), sql.vec("documents")) + _WORDS, _bit_pairs(BITS), DISTANCES, "<="))(_bit_pr(lambda df: hashes.pca_signs(df, BITS, rotate=False), BITS))
query("dedup_pr_pcae")(_bit_pr(lambda df: hashes.pca_signs(df, BITS), BITS))


@query("dedup_pr_trained")
def dedup_pr_trained(spark, sf):
    """The curve with a trained model."""
    df = materialize(vectors.documents(spark, sf).select("id", "vec"), "vectors")
    return _code_pr(spark, sf, en.encode(df, train.fit(df, DK, DM, DKS, iters=6)))


# ---- clusters, recommendation, transfer

_PART = sql.codes("parts", K, M, KS) + ",\n" + sql.tokens(M)


@query("cluster_parts", f"WITH RECURSIVE {_PART}, {sql.pairs()}, edges AS (SELECT a, b FROM pairs WHERE hits > 6), {sql.components('edges', 'SELECT id FROM codes')} SELECT id, component FROM comp")
def cluster_parts(spark, sf):
    return graph.cluster_all(codes_of(spark, sf, "parts"), M, 6)


_TURN = sql.codes("turns", K, M, KS) + ",\n" + sql.tokens(M)


@query("cluster_turns", f"WITH RECURSIVE {_TURN}, {sql.pairs()}, edges AS (SELECT a, b FROM pairs WHERE hits > 5), {sql.components('edges', 'SELECT id FROM codes')} SELECT id, component FROM comp")
def cluster_turns(spark, sf):
    return graph.cluster_all(codes_of(spark, sf, "turns"), M, 5)


@query("recommend_parts_for_customers", f"""WITH {_PART}, fav AS (SELECT DISTINCT o_custkey AS set_id, l_partkey AS id FROM orders JOIN lineitem ON l_orderkey = o_orderkey),
sc AS (SELECT f.set_id, d.id, count(*) AS score FROM fav f JOIN tokens q ON q.id = f.id JOIN tokens d ON d.token = q.token GROUP BY 1, 2)
SELECT set_id, id, score, CAST(rnk AS INTEGER) AS rnk FROM (SELECT set_id, id, score, row_number() OVER (PARTITION BY set_id ORDER BY score DESC, id) AS rnk FROM sc ANTI JOIN fav USING (set_id, id)) WHERE rnk <= 10""")
def recommend_parts_for_customers(spark, sf):
    bought = read_table(spark, sf, "orders").join(read_table(spark, sf, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("set_id"), F.col("l_partkey").alias("id"))
    df = materialize(vectors.parts(spark, sf, stored=True).select("id", "vec"), "vectors")
    sets = read_table(spark, sf, "orders").agg(F.approx_count_distinct("o_custkey").alias("n")).first().n
    return querysets.recommend(bought, en.encode(df, anchor(df, K, M, KS)), M, 10, sets)


_RES = _DT + """,
rs_ AS (SELECT qid, id, CAST(row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS INTEGER) AS rnk FROM (SELECT q.id AS qid, d.id, count(*) AS score FROM tokens q JOIN tokens d ON q.token = d.token AND q.id % 50 = 0 AND d.id % 50 <> 0 GROUP BY 1, 2) QUALIFY rnk <= 100),
ed AS (SELECT x.qid, x.id AS a, y.id AS b FROM rs_ x JOIN rs_ y ON x.qid = y.qid AND x.id <> y.id JOIN tokens s ON s.id = x.id JOIN tokens t ON t.id = y.id AND t.token = s.token GROUP BY 1, 2, 3 HAVING count(*) > 9),
reach(qid, id, seen) AS (SELECT qid, id, id FROM rs_ UNION SELECT r.qid, r.id, e.b FROM reach r JOIN ed e ON e.qid = r.qid AND e.a = r.seen),
best AS (SELECT r.qid, r.id, arg_min(r.seen, s.rnk) AS component FROM reach r JOIN rs_ s ON s.qid = r.qid AND s.id = r.seen GROUP BY 1, 2)"""


LEVELS = list(range(1, DM + 1))
_IN_LISTS = "SELECT p.a, p.b, count(*) AS s FROM (SELECT DISTINCT x.id AS a, y.id AS b FROM rs_ x JOIN rs_ y ON x.qid = y.qid AND x.id < y.id) p JOIN tokens s ON s.id = p.a JOIN tokens t ON t.id = p.b AND t.token = s.token GROUP BY 1, 2"
_LISTED = _RES[: _RES.index("ed AS (")].rstrip().rstrip(",")


@query("dedup_pr_lists", _pr_sql(_LISTED, _IN_LISTS, LEVELS, ">=").replace("pos AS (SELECT count(*) AS k FROM truth)", "pos AS (SELECT count(*) AS k FROM truth JOIN (SELECT DISTINCT x.id AS a, y.id AS b FROM rs_ x JOIN rs_ y ON x.qid = y.qid AND x.id < y.id) USING (a, b))"))
def dedup_pr_lists(spark, sf):
    """Pairs of items of one result list, at every threshold from 1 equal token to all."""
    codes = codes_of(spark, sf, "documents", DK, DM, DKS)
    lists = materialize(result_lists(codes).select("qid", "id"), "lists")
    met = lists.select("qid", F.col("id").alias("a")).join(lists.select("qid", F.col("id").alias("b")), "qid").where("a < b").select("a", "b").distinct()
    side = lambda x: codes.select(F.col("id").alias(x), *(F.col(c).alias(f"{c}_{x}") for c in ("c1", "c2", "fine")))
    both = met.join(side("a"), "a").join(side("b"), "b")
    row = lambda x: F.struct(*(F.col(f"{c}_{x}").alias(c) for c in ("c1", "c2", "fine"))).alias(x)
    marked = both.select(F.col("a").alias("left_id"), F.col("b").alias("right_id"), row("a"), row("b"))
    s = score.hits_pair("a", "b", DM).cast("long")
    pairs = materialize(marked.select(F.col("left_id"), F.col("right_id"), s.alias("s")).toDF("a", "b", "s"), "pairs")
    return metrics.pair_pr(pairs, duplicate_truth(spark, sf).join(pairs.select("a", "b"), ["a", "b"], "left_semi"), LEVELS)


def result_lists(codes):
    """(qid, id, rnk): the 100 best of each query, by equal tokens."""
    t = tk.flatten(codes)
    got = querysets.batch_search(t.where("id % 50 = 0").select(F.col("id").alias("set_id"), "token"), t.where("id % 50 <> 0"), top=100)
    return got.select(F.col("set_id").alias("qid"), "id", F.col("rnk").cast("int").alias("rnk"))


@query("dedup_search_results", f"WITH RECURSIVE {_RES} SELECT qid, id, rnk, component, component = id AS kept, CASE WHEN component <> id THEN component END AS dup_of FROM best JOIN rs_ USING (qid, id)")
def dedup_search_results(spark, sf):
    codes = codes_of(spark, sf, "documents", DK, DM, DKS)
    return graph.dedup_results(result_lists(codes), codes, DM, 9)


_LONGEST = _RES[: _RES.index("best AS (")] + "ln AS (SELECT doc_id AS id, length(text) AS n FROM documents),\nbest AS (SELECT r.qid, r.id, first(r.seen ORDER BY ln.n DESC, r.seen) AS component FROM reach r JOIN ln ON ln.id = r.seen GROUP BY 1, 2)"


@query("dedup_search_longest", f"WITH RECURSIVE {_LONGEST} SELECT qid, id, rnk, component, component = id AS kept, CASE WHEN component <> id THEN component END AS dup_of FROM best JOIN rs_ USING (qid, id)")
def dedup_search_longest(spark, sf):
    """Of duplicates in a list the longest text stays."""
    codes = codes_of(spark, sf, "documents", DK, DM, DKS)
    length = read_table(spark, sf, "documents").select(F.col("doc_id").alias("id"), F.length("text").alias("length"))
    return graph.dedup_results(result_lists(codes).join(length, "id"), codes, DM, 9, keep="longest")


def transfer_sql(view: str) -> str:
    """Codes of a view under the documents' model: model rows come first, by ids below all others."""
    rows = f"SELECT id - 1000000000 AS id, vec, grp FROM (SELECT * FROM ({sql.vec('documents')}) ORDER BY id LIMIT {DK + DKS}) UNION ALL SELECT id, vec, grp FROM ({sql.vec(view)})"
    return _D.replace(sql.vec("documents"), rows)


def transfer(spark, sf, view):
    docs = vectors.documents(spark, sf)
    return en.encode(vectors.VIEWS[view](spark, sf), anchor(docs, DK, DM, DKS))


query("transfer_model_pages", f"WITH {transfer_sql('pages')} SELECT id, c1, c2, fine FROM codes WHERE id >= 0")(lambda spark, sf: transfer(spark, sf, "pages"))

_MOVED = transfer_sql("pages") + ",\n" + sql.tokens(DM) + f",\npairs AS (SELECT a.id AS a, b.id AS b, count(*) AS hits FROM tokens a JOIN tokens b ON a.token = b.token AND a.id < b.id AND a.id >= 0 GROUP BY 1, 2),\nedges AS (SELECT a, b FROM pairs WHERE hits > 11)"


@query("dedup_transfer_pages", f"WITH RECURSIVE {_MOVED}, {sql.components('edges', 'SELECT id FROM codes WHERE id >= 0')} SELECT id, component FROM comp")
def dedup_transfer_pages(spark, sf):
    """Duplicate pages by codes that were learnt on documents."""
    return graph.cluster_all(transfer(spark, sf, "pages"), DM, 11)


THRESHOLDS, LEAST_ITEMS, MOST_ITEMS, MID = [3, 5, 7, 9, 11, 13], 10, 10_000, 10
_TAGGED = 1 << 44
_SWEEP = _DT + ",\n" + sql.stoplist(LEAST_ITEMS, MOST_ITEMS) + ",\n" + sql.pairs("s_") + f",\nedges AS (SELECT t * {_TAGGED} + a AS a, t * {_TAGGED} + b AS b FROM pairs CROSS JOIN (SELECT unnest({THRESHOLDS}) AS t) WHERE hits > t)"


@query("cluster_by_threshold", f"""WITH RECURSIVE {_SWEEP}, {sql.components('edges')}, ct AS (SELECT component // {_TAGGED} AS t, count(*) AS n FROM comp GROUP BY component),
et AS (SELECT a // {_TAGGED} AS t, count(*) AS edges FROM edges GROUP BY 1)
SELECT CAST(t AS BIGINT) AS threshold, any_value(edges) AS edges, count(*) AS components, count(*) FILTER (WHERE n >= {MID}) AS mid_size, max(n) AS largest FROM ct JOIN et USING (t) GROUP BY t""")
def cluster_by_threshold(spark, sf):
    """Edges, components and mid-size clusters by the threshold, under the published stoplist; one pass of components for all thresholds."""
    codes = materialize(doc_codes(spark, sf), "codes")
    place = F.shiftright("token", 16).bitwiseAND(F.lit(0xFFFF)).cast("int")
    kept = tk.stoplist(tk.flatten(codes), LEAST_ITEMS, MOST_ITEMS).groupBy("id").agg(F.collect_set(place).alias("kept"))
    fine = F.transform("fine", lambda f, i: F.when(F.array_contains("kept", i), f).otherwise(F.lit(blocks.MARK).cast("smallint")))
    counts, forest = blocks.hit_forests(codes.join(kept, "id").withColumn("fine", fine), DM, min(THRESHOLDS) + 1)
    step = F.explode(F.filter(F.array(*(F.lit(t).cast("long") for t in THRESHOLDS)), lambda t: t < F.col("s")))
    edges = counts.withColumn("threshold", step).groupBy("threshold").agg(F.sum("n").alias("edges"))
    tagged = forest.withColumn("t", step).select((F.col("t") * _TAGGED + F.col("a")).alias("a"), (F.col("t") * _TAGGED + F.col("b")).alias("b"))
    sizes = graph.components(tagged).groupBy("component").agg(F.count(F.lit(1)).alias("n")).select(F.expr(f"component DIV {_TAGGED}").alias("threshold"), "n")
    found = sizes.groupBy("threshold").agg(F.count(F.lit(1)).alias("components"), F.count_if(F.col("n") >= MID).alias("mid_size"), F.max("n").alias("largest"))
    return edges.join(found, "threshold")


_OVER = transfer_sql("benchmark") + ",\n" + sql.tokens(DM) + ",\n" + sql.codes("documents", DK, DM, DKS, p="d_") + ",\n" + sql.tokens(DM, "d_")


@query("benchmark_overlap", f"WITH {_OVER} SELECT set_id, id, score, CAST(rnk AS INTEGER) AS rnk FROM (SELECT q.id AS set_id, d.id, count(*) AS score, row_number() OVER (PARTITION BY q.id ORDER BY count(*) DESC, d.id) AS rnk FROM tokens q JOIN d_tokens d ON d.token = q.token AND q.id >= 0 GROUP BY 1, 2) WHERE rnk <= 5")
def benchmark_overlap(spark, sf):
    q = tk.flatten(transfer(spark, sf, "benchmark")).select(F.col("id").alias("set_id"), "token")
    return querysets.batch_search(q, doc_tokens(spark, sf), top=5)


_USER = sql.codes("users", 4, M, 12) + ",\n" + sql.tokens(M) + ",\n" + sql.pairs()


@query("similar_users", f"WITH {_USER}, s AS (SELECT a AS qid, b AS id, hits AS score FROM pairs UNION ALL SELECT b, a, hits FROM pairs) SELECT qid, id, score, CAST(rnk AS INTEGER) AS rnk FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS rnk FROM s) WHERE rnk <= 5")
def similar_users(spark, sf):
    p = graph.pair_hits(tk.flatten(codes_of(spark, sf, "users", 4, M, 12)))
    return search.top(p.select(F.col("a").alias("qid"), F.col("b").alias("id"), F.col("hits").alias("score")).unionAll(p.select("b", "a", "hits")), 5)


query("cells_customers", f"WITH {sql.codes('customers', K, M, KS)} SELECT c1, c2, count(*) AS n FROM codes GROUP BY 1, 2")(lambda spark, sf: search.cell_sizes(codes_of(spark, sf, "customers")))


@query("stoplist_cost", f"WITH {_DT}, n AS (SELECT token, count(DISTINCT id) AS n FROM tokens GROUP BY 1) SELECT CAST(hi AS INTEGER) AS hi, CAST(sum(n * (n - 1) // 2) AS BIGINT) AS pairs FROM n CROSS JOIN (SELECT unnest([20, 50, 100, 200, 1000]) AS hi) WHERE n BETWEEN 2 AND hi GROUP BY hi")
def stoplist_cost(spark, sf):
    """Joined pairs by the upper bound of the stoplist."""
    n = tk.frequencies(doc_tokens(spark, sf)).where("n >= 2")
    wide = n.agg(*(F.sum(F.when(F.col("n") <= h, F.expr("n * (n - 1) DIV 2"))).alias(str(h)) for h in (20, 50, 100, 200, 1000)))
    return wide.select(F.explode(F.array(*(F.struct(F.lit(h).alias("hi"), F.col(f"`{h}`").alias("pairs")) for h in (20, 50, 100, 200, 1000)))).alias("x")).select("x.hi", "x.pairs")
