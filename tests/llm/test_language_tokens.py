import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from codematch.llm import language, token_counts
from codematch.llm.joins import left_join


def test_documents_and_pages(spark):
    d = "/root/testdata/sf0.01"
    docs, pages = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/pages.parquet")
    got = language.documents_and_pages(docs, pages).toPandas()
    assert len(got) == docs.count() + pages.count()
    both = got.dropna(subset=["doc_id"]).merge(docs.select("doc_id", "lang").toPandas(), on="doc_id")
    assert both.lid_accepted.mean() > 0.99 and (both.lid_language == both.lang).mean() > 0.99


def test_text_outweighs_a_wrong_declaration_and_evidence_helps_short_texts(spark):
    d = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    wrong = docs.withColumn("said", F.when(F.pmod("doc_id", F.lit(10)) == 0, F.lit("fr")).otherwise(F.col("lang"))).where("n_chars > 400")
    got = language.identify(wrong, declared=F.col("said"), host=F.col("source")).where("lang <> said").toPandas()
    assert len(got) > 20 and (got.lid_language == got.lang).mean() > 0.97
    profiles = language.learn(docs.select("text", F.col("lang").alias("declared")))
    rows = spark.createDataFrame([("ta", "de", "h1"), ("ta", "es", "h1"), ("ta", "es-MX", "h1")], "text string, said string, h string")
    short = [r.lid_language for r in language.identify(rows, declared=F.col("said"), host=F.col("h"), profiles=profiles).collect()]
    assert short[1] == short[2] == "es" and short[0] in ("de", "es")


def test_host_prior_is_smoothed(spark):
    rows = [("z", "a.z", 0)] * 98 + [("z", "a.z", 1)] * 2 + [("z", "b.z", 1)] + [("y", "c.y", 1)] * 50
    table, base = language._host_table(language._host_counts(spark.createDataFrame(rows, "suffix string, host string, top int"), 2), 2)
    prior = {r.lid_place: np.exp(r.lid_prior) for r in table.collect()}
    assert prior["a.z"][0] > 0.9 and prior["c.y"][1] > 0.7
    assert 0.5 < prior["b.z"][0] < prior["a.z"][0]  # one row doesn't outweigh its suffix
    assert all(abs(p.sum() - 1) < 1e-9 for p in prior.values())


def test_hosts_beyond_a_broadcast_get_the_same_priors(spark):
    rows = [(None, "hot", 0)] * 50 + [("z", f"h{i % 40}", i % 2) for i in range(80)] + [(None, None, 1), ("z", "none", None)]
    seen = spark.createDataFrame(rows, "suffix string, host string, top int")
    table, _ = language._host_table(language._host_counts(seen, 2), 2)
    work = seen.select(F.col("suffix").alias("lid_suffix"), F.col("host").alias("lid_host"))
    joined = lambda most: left_join(work, table, {"lid_suffix": "lid_zone", "lid_host": "lid_place"}, "lid_rows", "lid_prior", most, 10)
    want, got = (sorted(map(repr, joined(most).collect())) for most in (1000, 3))
    assert want == got and len(got) == len(rows)


def posterior(languages, texts, declared, places, hosts, base):
    """Plain numpy: the posterior of each row from its evidence; a row without grams has none."""
    out = []
    for e, d, h in zip(texts, declared, places, strict=True):
        if not len(e):
            out.append(None)
            continue
        mean, n = np.array(e[:-1]), e[-1]
        said = [0.0 if d not in languages else np.log(language.DECLARED if d == x else (1 - language.DECLARED) / (len(languages) - 1)) for x in languages]
        logit = mean * min(n, language.EFFECTIVE) + said + hosts.get(h, base)
        p = np.exp(logit - logit.max())
        out.append((languages[int(np.argmax(logit))], float(p.max() / p.sum())))
    return out


def test_identify_equals_plain_bayes(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", F.col("lang").alias("said"), "source")
    rows = docs.unionAll(spark.createDataFrame([(-1, "t", "de", None), (-2, None, "de", "x"), (-3, "le la", "en", "fr.x"), (-4, "12 34", None, None)], docs.schema))
    profiles = language.learn(docs.select("text", F.col("said").alias("declared")))
    data = rows.orderBy("doc_id").collect()
    texts = [profiles.evidence(r.text.encode() if r.text else None) for r in data]
    counts = {}
    for r, e in zip(data, texts, strict=True):
        if e:
            counts.setdefault(r.source, np.zeros(len(profiles.languages)))[int(np.argmax(e[:-1]))] += 1
    base = sum(counts.values()) + 1
    base = base / base.sum()
    total = sum(counts.values())  # all hosts are of the one null suffix
    zone = (total + language.STRENGTH * base) / (total.sum() + language.STRENGTH)
    hosts = {h: np.log((c + language.STRENGTH * zone) / (c.sum() + language.STRENGTH)) for h, c in counts.items()}
    want = posterior(profiles.languages, texts, [r.said for r in data], [r.source for r in data], hosts, np.log(base))
    got = {r.doc_id: r for r in language.identify(rows, declared=F.col("said"), host=F.col("source"), profiles=profiles).collect()}
    for r, e, w in zip(data, texts, want, strict=True):
        g = got[r.doc_id]
        if w is None:
            assert g.lid_language is None and g.lid_probability == 0 and not g.lid_accepted
        else:
            assert g.lid_language == w[0] and abs(g.lid_probability - w[1]) < 1e-9
            assert g.lid_accepted == (max(e[:-1]) > 0 and w[1] >= language.LEAST)


def test_odd_pages(spark):
    html = [None, "", "<html lang='de'>", "<p>the cat and the dog</p>", "<html lang=en-US><script>der die das</script>the cat and the dog of this house"]
    pages = spark.createDataFrame([(i if i else None, f"http://h{i}.de/x" if i % 2 else None, h, "x") for i, h in enumerate(html)], "page_id long, url string, html string, lid_text string")
    docs = spark.createDataFrame([(1, "the cat and the dog " * 5, "en", None)], "doc_id long, text string, lang string, source string")
    got = language.documents_and_pages(docs, pages).collect()
    assert len(got) == 6 and {r.page_id: r.lid_accepted for r in got if r.doc_id is None} == {None: False, 1: False, 2: False, 3: True, 4: True}
    assert language.documents_and_pages(docs.limit(0), pages.limit(0)).count() == 0
    assert language.documents_and_pages(docs, pages.limit(0)).count() == 1


def test_odd_language_rows(spark):
    rows = spark.createDataFrame([(None, None, None, 1), ("", "en", "h", 1), ("123 ###", "en", "h", 1), ("the and of", "xx", None, 1), ("the and of " * 30_000, "en", "h", 1)], "text string, lang string, source string, lid_text int")
    got = language.identify(rows, declared=F.col("lang"), host=F.col("source")).collect()
    accepted = {r.text: r.lid_accepted for r in got}  # rows are in no order
    assert len(got) == 5 and [accepted[t] for t in (None, "", "123 ###")] == [False] * 3 and accepted["the and of " * 30_000]
    assert language.identify(rows.limit(0), declared=F.col("lang")).count() == 0


@pytest.mark.parametrize("rule", token_counts.RULES)
def test_allocation_equals_counting_bytes(rule):
    rng = random.Random(5)
    for _ in range(200):
        ends = np.cumsum([rng.randint(1, 6) for _ in range(rng.randint(0, 30))])
        total = int(ends[-1]) if len(ends) else 0
        cuts = sorted({0, total, *(rng.randint(0, total) for _ in range(4))})
        sections = [("s", a, b) for a, b in zip(cuts, cuts[1:], strict=False)]
        want = [0.0] * len(sections)
        for s, e in zip([0, *ends.tolist()], ends.tolist(), strict=False):
            parts = [max(0, min(e, b) - max(s, a)) for _, a, b in sections]
            if rule == "share":
                want = [w + p / (e - s) for w, p in zip(want, parts, strict=True)]
            elif rule == "most":
                want[parts.index(max(parts))] += 1
            else:
                want[next(i for i, (_, a, b) in enumerate(sections) if a <= s < b)] += 1
        assert np.allclose(token_counts.allocate(ends, sections, rule), want)


def test_documents_are_encoded_whole(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").union(spark.createDataFrame([(None, None), (-1, ""), (-2, "\n\n"), (-3, "a" * 30_000), (-4, "é😀\nx")], "doc_id long, text string"))
    got = token_counts.section_tokens(docs).collect()
    encoder = token_counts.Encoder(token_counts.read_ranks(token_counts.VOCABULARY))
    texts = {r.doc_id: r.text for r in docs.collect()}
    assert len(got) == len(texts)
    for r in got:
        text = texts[r.doc_id] or ""
        ids = encoder.encoding.encode_ordinary(text)
        assert r.n_tokens == len(ids) == sum(s.n_tokens for s in r.sections)
        assert sum(s.n_bytes for s in r.sections) == len(text.encode())
    text = "é😀 tokens split\nin two"
    spans = token_counts.character_spans(text, encoder.ends(text))
    assert spans[0][0] == 0 and spans[-1][1] == len(text) and all(s < e for s, e in spans)
    public = pytest.importorskip("public_tokenizers")
    assert token_counts.PATTERN == public.PATTERN


def test_languages_and_profiles_come_from_all_rows(spark):
    many = spark.range(16_000).select(F.concat(F.lit("the cat and the dog "), F.col("id")).alias("text"), F.lit("en").alias("declared"))
    few = spark.range(24).select(F.concat(F.lit("ja taas kissa oli "), F.col("id")).alias("text"), F.lit("fi").alias("declared"))
    assert language.learn(many.unionAll(few)).languages == ["en", "fi"]
    copies = spark.range(3000).select(F.lit("zzz qqq xxx").alias("text"), F.lit("fi").alias("declared"))
    once, often = (language.learn(few.unionAll(c)) for c in (copies.limit(1), copies))
    assert once.languages == often.languages and np.array_equal(once.table, often.table)
    texts = [r.text for r in few.unionAll(copies.limit(1)).collect()]
    want = sum(np.bincount(language.gram_places(t.encode()), minlength=language.GRAMS) for t in texts) + 0.2
    assert np.allclose(once.table[:, 0], np.log(want / want.sum()), atol=1e-5)


def test_sections_of_empty_tables_and_clashing_columns(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert token_counts.section_tokens(empty).count() == 0
    odd = spark.createDataFrame([(1, "a b\nc", 9, "x"), (1, "a b\nc", 9, "x"), (None, "a", 9, "x")], "doc_id long, text string, n_tokens int, sections string")
    plain = token_counts.section_tokens(odd.select("doc_id", "text")).collect()
    got = token_counts.section_tokens(odd).collect()
    assert sorted(map(repr, got)) == sorted(map(repr, plain)) and len(got) == 3
