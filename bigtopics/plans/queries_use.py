"""Registered queries: retrieval, clicks, measures, baselines, training runs, and the operators around them."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F


from ..functions.rand import uniform
from ..functions.text import strip_tags, words
from ..operators import baselines, clicks, counts, measures, prepare, retrieval
from ..sources.files import round_trip, settle
from ..streaming import streams
from . import training
from .queries import _SPLIT, _U, ALPHA, BETA, DOCTOK, STATE, TOK, TOPICS, _doc_tokens, _model, _state, _t, _tokens, _vocab_size, query

# --- retrieval --------------------------------------------------------------------------------------

_BG = f", r AS (SELECT psi.topic, {ALPHA} / (psi.n + v * {BETA}) AS r FROM psi, v), g AS (SELECT w.word_id, sum((coalesce(phi.n, 0) + {BETA}) * r) AS g FROM (SELECT DISTINCT word_id FROM phi) w CROSS JOIN r LEFT JOIN phi ON phi.word_id = w.word_id AND phi.topic = r.topic GROUP BY w.word_id)"
_LIKE = _BG + f", q AS (SELECT * FROM theta WHERE doc_id % 100 = 0), lq AS (SELECT doc_id, sum(n) AS len FROM q GROUP BY doc_id), own AS (SELECT q.doc_id, phi.word_id, sum(q.n * phi.n / (psi.n + v * {BETA})) AS own FROM q JOIN psi ON psi.topic = q.topic JOIN phi ON phi.topic = q.topic CROSS JOIN v GROUP BY ALL), flat AS (SELECT doc_id, sum(q.n * {BETA} / (psi.n + v * {BETA})) AS flat FROM q JOIN psi USING (topic), v GROUP BY doc_id), wl AS (SELECT doc_id, word_id, (own + flat + g) / (len + {ALPHA * TOPICS}) AS p FROM own JOIN flat USING (doc_id) JOIN lq USING (doc_id) JOIN g USING (word_id))"


def _likelihood(spark, d, ids="doc_id % 100 = 0"):
    _, theta, phi, psi, alpha, v = _model(spark, d)
    return retrieval.word_likelihood(theta.filter(ids), phi, psi, alpha, BETA, v)


def _features(spark, d, ids="doc_id % 100 = 0"):
    _, theta, phi, psi, alpha, v = _model(spark, d)
    return retrieval.topic_features_blocks(theta.filter(ids), phi, psi, alpha, BETA, v)


@query(STATE + _LIKE + " SELECT doc_id, word_id, round(p, 9) AS p FROM wl")
def word_likelihood(spark, d):
    return _likelihood(spark, d).withColumn("p", F.round("p", 9))


@query(STATE + _LIKE + " SELECT doc_id, word_id, round(p, 9) AS p, row_number() OVER (PARTITION BY doc_id ORDER BY round(p, 9) DESC, word_id) AS rank FROM wl QUALIFY rank <= 30")
def topic_features_top30(spark, d):
    return _features(spark, d)


@query()
def word_likelihood_all(spark, d):
    """word_likelihood of every basket; the query with SQL has the ids divisible by 100."""
    return _likelihood(spark, d, "true").withColumn("p", F.round("p", 9))


@query()
def topic_features_all(spark, d):
    """topic_features_top30 of every basket."""
    return _features(spark, d, "true")


VEC = ", f AS (SELECT doc_id, word AS word_id, count(*) AS tf FROM t GROUP BY ALL), x AS (SELECT doc_id, word_id, f.tf * ln((SELECT count(DISTINCT doc_id) FROM t) / df) AS x FROM f JOIN wc ON word = word_id), vec AS (SELECT doc_id, word_id, x / sqrt(sum(x * x) OVER (PARTITION BY doc_id)) AS w FROM x QUALIFY sum(x * x) OVER (PARTITION BY doc_id) > 0)"
_Q = f", qt AS (SELECT item_id, unnest({_SPLIT.format('text')}) AS word FROM benchmark), qf AS (SELECT item_id, word, count(*) AS c FROM qt GROUP BY ALL), qv AS (SELECT item_id AS query_id, word AS word_id, c / sqrt(sum(c * c) OVER (PARTITION BY item_id)) AS qw FROM qf), sc AS (SELECT query_id, doc_id, sum(qw * w) AS score FROM qv JOIN vec USING (word_id) GROUP BY ALL)"
_TOP10 = ", top AS (SELECT query_id, doc_id, round(score, 9) AS score, row_number() OVER (PARTITION BY query_id ORDER BY round(score, 9) DESC, doc_id) AS rank FROM sc QUALIFY rank <= 10)"


def _vectors(spark, d):
    return retrieval.word_vectors(_doc_tokens(spark, d).withColumnRenamed("word", "word_id"))


def _query_vectors(spark, d):
    t = prepare.tokenize(_t(spark, d, "benchmark").withColumnRenamed("item_id", "doc_id"), "doc_id", "text")
    return retrieval.word_vectors(t.withColumnRenamed("word", "word_id"), "tf")


@query(DOCTOK + VEC + " SELECT doc_id, count(*) AS words, round(max(w), 9) AS top, round(sum(w), 6) AS total FROM vec GROUP BY doc_id")
def tfidf_vectors(spark, d):
    return _vectors(spark, d).groupBy("doc_id").agg(F.count(F.lit(1)).alias("words"), F.round(F.max("w"), 9).alias("top"), F.round(F.sum("w"), 6).alias("total"))


@query(DOCTOK + VEC + _Q + " SELECT query_id, doc_id, round(score, 6) AS score FROM sc")
def cosine_scores(spark, d):
    return retrieval.cosine_sparse(_query_vectors(spark, d), _vectors(spark, d)).withColumn("score", F.round("score", 6))


@query("SELECT a.vec_id AS a, b.vec_id AS b, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 5) AS score FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id < b.vec_id AND a.vec_id % 20 = 0")
def dense_cosine(spark, d):
    e = _t(spark, d, "embeddings")
    a, b = e.filter("vec_id % 20 = 0").select(F.col("vec_id").alias("a"), F.col("embedding").alias("x"), "label"), e.select(F.col("vec_id").alias("b"), F.col("embedding").alias("y"), "label")
    return a.join(b, "label").filter("a < b").select("a", "b", F.round(retrieval.cosine_dense(F.col("x"), F.col("y")), 5).alias("score"))


@query()
def dense_topk(spark, d):
    """The ten nearest of all other embeddings for each query vector; dense_cosine has scores within a label alone."""
    e = _t(spark, d, "embeddings").select(F.col("vec_id").alias("doc_id"), F.transform("embedding", lambda x: x.cast("double")).alias("x"))
    norm = F.sqrt(F.aggregate("x", F.lit(0.0), lambda s, x: s + x * x))
    unit = e.withColumn("norm", norm).select("doc_id", F.sequence(F.lit(0), F.size("x") - 1).alias("words"), F.transform("x", lambda x: F.when(F.col("norm") > 0, x / F.col("norm")).otherwise(0.0)).alias("w"))
    return retrieval.search_blocks(unit.filter("doc_id % 20 = 0"), unit, 10).withColumn("score", F.round("score", 5))


@query(DOCTOK + VEC + " SELECT word_id, count(*) AS n, round(max(w), 9) AS max_w FROM vec GROUP BY word_id")
def postings_stats(spark, d):
    return retrieval.build_postings(_vectors(spark, d)).select("word_id", "n", F.round("max_w", 9).alias("max_w"))


@query(DOCTOK + VEC + _Q + _TOP10 + " SELECT query_id, doc_id, round(score, 6) AS score, rank FROM top")
def retrieval_topk(spark, d):
    return retrieval.rank(retrieval.cosine_sparse(_query_vectors(spark, d), _vectors(spark, d)), 10).withColumn("score", F.round("score", 6))


@query(DOCTOK + VEC + _Q + _TOP10 + " SELECT query_id, doc_id, round(score, 6) AS score, rank FROM top")
def wand_topk(spark, d):
    return retrieval.weak_and(_query_vectors(spark, d), _vectors(spark, d), 10).select("query_id", "doc_id", F.round("score", 6).alias("score"), "rank")


@query()
def wand_work(spark, d):
    """Documents scored in full by Weak-AND beside those an exhaustive ranking scores."""
    q, v = _query_vectors(spark, d), _vectors(spark, d)
    done = retrieval.weak_and(q, v, 10).select("query_id", "scored").groupBy("query_id").agg(F.max("scored").alias("most_in_a_shard"))
    return retrieval.cosine_sparse(q, v).groupBy("query_id").agg(F.count(F.lit(1)).alias("exhaustive")).join(done, "query_id")


_QRELS = ", rel AS (SELECT item_id AS query_id, doc_id, 1.0 AS rel FROM benchmark JOIN documents ON contains(documents.text, substr(benchmark.text, 1, 60)))"


def _qrels(spark, d):
    b = _t(spark, d, "benchmark").select(F.col("item_id").alias("query_id"), F.substring("text", 1, 60).alias("head"))
    docs = _t(spark, d, "documents").select("doc_id", "text")
    # benchmark is a small, fixed list of passages
    return docs.join(F.broadcast(b), F.expr("contains(text, head)")).select("query_id", "doc_id", F.lit(1.0).alias("rel"))


@query(DOCTOK + VEC + _Q + _TOP10 + _QRELS + ", n AS (SELECT query_id, count(DISTINCT doc_id) AS k FROM rel GROUP BY query_id), h AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY rank) / rank AS prec FROM top JOIN (SELECT DISTINCT query_id, doc_id FROM rel) USING (query_id, doc_id)), ap AS (SELECT query_id, sum(prec) AS s FROM h GROUP BY query_id) SELECT count(*) AS queries, round(avg(coalesce(s, 0) / k), 6) AS map FROM n LEFT JOIN ap USING (query_id)")
def map_score(spark, d):
    return retrieval.mean_average_precision(retrieval_topk(spark, d), _qrels(spark, d))


def whole_passages(benchmark, docs):
    """query_id, doc_id, rel: documents that hold a whole passage; white space is left out on both sides."""
    plain = F.regexp_replace("text", r"\s+", "")
    b = benchmark.select(F.col("item_id").alias("query_id"), plain.alias("passage")).filter("passage <> ''")
    # benchmark is a small, fixed list of passages
    return docs.select("doc_id", plain.alias("plain")).join(F.broadcast(b), F.expr("contains(plain, passage)")).select("query_id", "doc_id", F.lit(1.0).alias("rel"))


@query()
def map_score_whole(spark, d):
    """map_score with relevance by the whole passage; the query with SQL goes by its first 60 characters."""
    return retrieval.mean_average_precision(retrieval_topk(spark, d), whole_passages(_t(spark, d, "benchmark"), _t(spark, d, "documents")))


@query()
def expanded_retrieval(spark, d):
    """Baskets as queries, mixed with their topic words, against all other baskets."""
    t, asked = _tokens(spark, d), "doc_id % 20 = 0"
    q = retrieval.word_vectors(t.filter(asked), "tf")
    feats = retrieval.topic_features(_likelihood(spark, d, asked), 30)
    asked, docs = (retrieval.as_lists(x) for x in (retrieval.expand_query(q, feats), retrieval.word_vectors(t, "tf")))
    return retrieval.search_blocks(settle(asked, "asked"), settle(docs, "docs"), 10).filter("score > 0")


# --- clicks -----------------------------------------------------------------------------------------


def _impressions(spark, d, label="toxic"):
    return _t(spark, d, "documents").join(_t(spark, d, "labels").select("doc_id", F.col(label).cast("double").alias("label")), "doc_id")


@query(f"SELECT doc_id, len(list_distinct({_SPLIT.format('text')})) + 3 AS feats FROM documents JOIN labels USING (doc_id)")
def click_feature_counts(spark, d):
    return clicks.click_features(_impressions(spark, d)).select("doc_id", F.size("feats").cast("bigint").alias("feats"))


@query()
def click_model_auc(spark, d):
    """Held-out AUC of the L1 model without topic features."""
    train, test = clicks.split_impressions(clicks.click_features(_impressions(spark, d)), test=0.3)
    return measures.auc(clicks.score_clicks(clicks.fit_click_model(train), test))




@query("WITH ads AS (SELECT o_custkey % 50 AS query, o_orderkey AS ad, o_totalprice AS bid, 1 / pow(2, o_orderkey % 5) AS rate FROM orders), v AS (SELECT *, round(bid * rate, 9) AS value FROM ads) SELECT query, ad, row_number() OVER w AS place, round(coalesce(lead(value) OVER w, 0) / rate, 6) AS price FROM v WINDOW w AS (PARTITION BY query ORDER BY value DESC, ad)")
def second_price(spark, d):
    ads = _t(spark, d, "orders").select((F.col("o_custkey") % 50).alias("query"), F.col("o_orderkey").alias("ad"), F.col("o_totalprice").alias("bid"), (1 / F.pow(F.lit(2.0), F.col("o_orderkey") % 5)).alias("rate"))
    return clicks.rank_ads(ads).select("query", "ad", "place", F.round("price", 6).alias("price"))


@query("SELECT hour(ts)::BIGINT AS hour, count(*) AS shown, count_if(event_type = 'click')::BIGINT AS clicks, round(count_if(event_type = 'click') / count(*), 6) AS rate FROM events WHERE event_type IN ('view', 'click') GROUP BY ALL")
def ctx_hourly_ctr(spark, d):
    return clicks.hourly_context(_t(spark, d, "events"))


# --- measures ---------------------------------------------------------------------------------------

_PMI = ", tw AS (SELECT topic, word_id FROM phi QUALIFY row_number() OVER (PARTITION BY topic ORDER BY n DESC, word_id) <= 10), s AS (SELECT DISTINCT doc_id, word_id FROM tok), df AS (SELECT word_id, count(*) AS df FROM s GROUP BY word_id), pr AS (SELECT x.topic, x.word_id AS a, y.word_id AS b FROM tw x JOIN tw y ON x.topic = y.topic AND x.word_id < y.word_id), co AS (SELECT a, b, count(*) AS co FROM (SELECT DISTINCT a, b FROM pr) JOIN s x ON x.word_id = a JOIN s y ON y.word_id = b AND y.doc_id = x.doc_id GROUP BY ALL), pmi AS (SELECT topic, round(avg(ln((coalesce(co, 0) + 1) * (SELECT count(DISTINCT doc_id) FROM s) / (da.df * db.df))), 6) AS pmi FROM pr LEFT JOIN co USING (a, b) JOIN df da ON da.word_id = a JOIN df db ON db.word_id = b GROUP BY topic)"


@query(STATE + _PMI + " SELECT topic, pmi FROM pmi")
def topic_pmi(spark, d):
    tz, _, phi, _, _, _ = _model(spark, d)
    return measures.topic_pmi(phi, tz)


@query(STATE + _PMI + " SELECT floor(pmi / 0.5)::BIGINT AS bucket, count(*) AS topics, round(count(*) / (SELECT count(*) FROM pmi), 6) AS share FROM pmi GROUP BY ALL")
def pmi_hist(spark, d):
    return measures.pmi_histogram(topic_pmi(spark, d))


@query(STATE + f", tp AS (SELECT t.doc_id, psi.topic, (coalesce(theta.n, 0) + {ALPHA}) / (sum(coalesce(theta.n, 0)) OVER (PARTITION BY t.doc_id) + {ALPHA * TOPICS}) AS p FROM (SELECT DISTINCT doc_id FROM tok) t CROSS JOIN psi LEFT JOIN theta ON theta.doc_id = t.doc_id AND theta.topic = psi.topic), pw AS (SELECT tz.doc_id, tz.pos, sum(p * (coalesce(phi.n, 0) + {BETA}) / (psi.n + v * {BETA})) AS pw FROM tz JOIN tp USING (doc_id) JOIN psi ON psi.topic = tp.topic LEFT JOIN phi ON phi.word_id = tz.word_id AND phi.topic = tp.topic CROSS JOIN v GROUP BY ALL) SELECT count(*) AS tokens, round(exp(-avg(ln(pw))), 4) AS perplexity FROM pw")
def perplexity(spark, d):
    tz, theta, phi, psi, _, v = _model(spark, d)
    full = tz.select("doc_id").distinct().crossJoin(F.broadcast(psi.select("topic"))).join(theta, ["doc_id", "topic"], "left").na.fill(0, ["n"])  # K rows
    p = full.withColumn("p", (F.col("n") + ALPHA) / (F.sum("n").over(Window.partitionBy("doc_id")) + ALPHA * TOPICS)).select("doc_id", "topic", "p")
    return measures.perplexity(tz, p, phi, psi, BETA, v)


_CORES = (1, 2, 4, 8)
_SHARD = "floor(" + _U.format("'7|word|' || word_id") + " * cores)"


@query(TOK + f", w AS (SELECT word_id, count(*) AS tf FROM tok GROUP BY word_id), l AS (SELECT cores, {_SHARD} AS shard, sum(tf) AS load FROM w, (SELECT unnest({list(_CORES)})::BIGINT AS cores) GROUP BY ALL), s AS (SELECT cores, max(load) * 1e-6::DOUBLE AS seconds FROM l GROUP BY cores), o AS (SELECT seconds AS one FROM s WHERE cores = 1) SELECT cores, seconds, round(one / seconds, 6) AS speedup, round(one / seconds / cores, 6) AS efficiency FROM s, o")
def speedup_table(spark, d):
    """Speedup of a sweep over all baskets with a word shard on each core, a microsecond a token: the largest shard sets the time."""
    tf = _tokens(spark, d).groupBy("word_id").agg(F.count(F.lit(1)).alias("tf")).withColumn("cores", F.explode(F.array(*(F.lit(c).cast("bigint") for c in _CORES))))
    load = tf.groupBy("cores", F.floor(uniform(F.lit("word"), "word_id") * F.col("cores")).alias("shard")).agg(F.sum("tf").alias("load"))
    return measures.speedup(load.groupBy("cores").agg((F.max("load") * F.lit(1e-6)).alias("seconds")), 1)


@query("WITH s AS (SELECT n_chars % 100 AS score, toxic AS y FROM documents JOIN labels USING (doc_id)), r AS (SELECT y, (rank() OVER (ORDER BY score) + (count(*) OVER (PARTITION BY score) - 1) / 2) AS rk FROM s) SELECT sum(y)::BIGINT AS pos, count_if(y = 0)::BIGINT AS neg, round((sum(rk * y) - sum(y) * (sum(y) + 1) / 2) / (sum(y) * count_if(y = 0)), 6) AS auc FROM r")
def auc(spark, d):
    return measures.auc(_impressions(spark, d).select((F.col("n_chars") % 100).alias("score"), F.col("label").cast("bigint").alias("label")))


@query(TOK + ", w AS (SELECT word_id, count(*) AS f, count_if(doc_id % 2 = 0) AS g FROM tok GROUP BY word_id), t AS (SELECT sum(f)::DOUBLE AS f0, sum(g)::DOUBLE AS g0, count(*)::DOUBLE AS v FROM w), c AS (SELECT doc_id % 20 AS iter, avg(ln((f + 1) / (f0 + v))) AS x, avg(ln((g + 1) / (g0 + v))) AS y FROM tok JOIN w USING (word_id), t GROUP BY ALL) SELECT round(max(abs(x - y)), 6) AS max_gap, round(avg(abs(x - y)), 6) AS mean_gap, round(avg(abs((x - y) / y)), 9) AS relative_gap FROM c")
def curve_gap(spark, d):
    """Gap of two curves of the log-likelihood a token over twenty parts of the baskets: by word counts of all baskets, and of those with even ids."""
    t = _tokens(spark, d)
    w = t.groupBy("word_id").agg(F.count(F.lit(1)).alias("f"), F.count_if(F.col("doc_id") % 2 == 0).alias("g"))
    total = w.agg(F.sum("f").alias("f0"), F.sum("g").alias("g0"), F.count(F.lit(1)).alias("v"))
    score = lambda n, whole: F.log((F.col(n) + 1) / (F.col(whole) + F.col("v")))
    j = t.join(w, "word_id").crossJoin(F.broadcast(total))
    curves = settle(j.groupBy((F.col("doc_id") % 20).alias("iter")).agg(F.avg(score("f", "f0")).alias("x"), F.avg(score("g", "g0")).alias("y")), "curves")
    return measures.curve_gap(curves.select("iter", F.col("x").alias("ll")), curves.select("iter", F.col("y").alias("ll")))


_LAB = ", a AS (SELECT z AS topic, o_orderpriority AS label, count(*) AS n FROM tz JOIN orders ON o_orderkey = doc_id GROUP BY ALL)"


def _assigned(spark, d):
    o = _t(spark, d, "orders").select(F.col("o_orderkey").alias("doc_id"), F.col("o_orderpriority").alias("label"))
    return _state(spark, d).join(o, "doc_id").groupBy(F.col("z").alias("topic"), "label").agg(F.count(F.lit(1)).alias("n"))


@query(STATE + _LAB + " SELECT sum(n)::BIGINT AS tokens, round(sum(top) / sum(n), 6) AS purity FROM (SELECT topic, max(n) AS top, sum(n) AS n FROM a GROUP BY topic)")
def topic_purity(spark, d):
    return measures.topic_purity(_assigned(spark, d))


@query(STATE + _LAB + ", t AS (SELECT topic, sum(n) AS nt FROM a GROUP BY topic), l AS (SELECT label, sum(n) AS nl FROM a GROUP BY label), w AS (SELECT sum(n) AS s FROM a) SELECT round((SELECT sum(n / s * ln(n * s / (nt * nl))) FROM a JOIN t USING (topic) JOIN l USING (label), w) / sqrt((SELECT -sum(nt / s * ln(nt / s)) FROM t, w) * (SELECT -sum(nl / s * ln(nl / s)) FROM l, w)), 6) AS nmi")
def label_nmi(spark, d):
    return measures.nmi(_assigned(spark, d)).withColumn("nmi", F.round("nmi", 6))


# --- baselines and training -------------------------------------------------------------------------

_SETS = TOK + ", s AS (SELECT DISTINCT doc_id, p_brand AS word FROM tok JOIN part ON p_partkey = word_id), f AS (SELECT word FROM s GROUP BY word HAVING count(*) >= 50), live AS (SELECT * FROM s WHERE word IN (SELECT word FROM f)), p AS (SELECT x.word AS a, y.word AS b, count(*) AS support FROM live x JOIN live y ON x.doc_id = y.doc_id AND x.word < y.word GROUP BY ALL HAVING count(*) >= 50)"


def _brand_words(spark, d):
    names = _t(spark, d, "part").select(F.col("p_partkey").alias("word_id"), F.col("p_brand").alias("word"))
    return _tokens(spark, d).join(names, "word_id").select("doc_id", "word")


def _brand_sets(spark, d):
    return _brand_words(spark, d).distinct()


@query(_SETS + " SELECT a, b, support FROM p")
def word_pairs_frequent(spark, d):
    return baselines.frequent_word_sets(_brand_words(spark, d), 50)


@query(_SETS + " SELECT x.word AS a, y.word AS b, z.word AS c, count(*) AS support FROM live x JOIN live y ON x.doc_id = y.doc_id AND x.word < y.word JOIN live z ON z.doc_id = x.doc_id AND y.word < z.word WHERE (x.word, y.word) IN (SELECT (a, b) FROM p) AND (x.word, z.word) IN (SELECT (a, b) FROM p) AND (y.word, z.word) IN (SELECT (a, b) FROM p) GROUP BY ALL HAVING count(*) >= 50")
def word_triples_frequent(spark, d):
    return baselines.frequent_word_sets(_brand_words(spark, d), 50, 3)


@query(_SETS + ", u AS (SELECT * FROM s WHERE doc_id % 10 = 0) SELECT count(DISTINCT u.doc_id) AS queries, count(DISTINCT h.doc_id) AS covered FROM u LEFT JOIN (SELECT DISTINCT x.doc_id FROM u x JOIN p ON p.a = x.word JOIN u y ON y.doc_id = x.doc_id AND y.word = p.b) h ON h.doc_id = u.doc_id")
def word_set_coverage(spark, d):
    s = _brand_sets(spark, d)
    return baselines.coverage(baselines.frequent_word_sets(s, 50), s.filter("doc_id % 10 = 0"))


@query()
def word_set_coverage_all(spark, d):
    """word_set_coverage of every basket."""
    s = _brand_sets(spark, d)
    return baselines.coverage(baselines.frequent_word_sets(s, 50), s)


def _settings(spark, d, **more):
    return training.Settings(topics=TOPICS, vocab_size=_vocab_size(_tokens(spark, d)), alpha=ALPHA, beta=BETA, **more)


@query()
def train_grid_relaxed(spark, d):
    return training.GridTrainer(spark, _settings(spark, d)).start(_tokens(spark, d)).train(2).model()[1]


@query()
def train_grid_diagonal(spark, d):
    return training.GridTrainer(spark, _settings(spark, d, shards=2, sync="diagonal")).start(_tokens(spark, d)).train(1).model()[1]


@query()
def train_grid_segment(spark, d):
    return training.GridTrainer(spark, _settings(spark, d, shards=2, sync="segment")).start(_tokens(spark, d)).train(1).model()[1]


@query()
def train_two_configurations(spark, d):
    return training.GridTrainer(spark, _settings(spark, d, configs=2, merge_every=2, prior_from=2)).start(_tokens(spark, d)).train(2).model()[1]


@query()
def train_replicated(spark, d):
    # words by rank, so that ids are dense
    t = settle(_tokens(spark, d), "tokens")
    dense = prepare.encode(t.withColumn("word", F.col("word_id").cast("string")).drop("word_id"), prepare.build_vocab(prepare.word_counts(t.withColumn("word", F.col("word_id").cast("string")))))
    s = _settings(spark, d)
    return counts.count_topic(training.ReplicatedTrainer(spark, s).start(dense).train(2).state)


# --- operators around the methods -------------------------------------------------------------------


@query("SELECT doc_id, lang FROM documents WHERE lang = 'de' AND n_chars BETWEEN 500 AND 5000")
def scan_partition_filter(spark, d):
    return _t(spark, d, "documents").filter((F.col("lang") == "de") & F.col("n_chars").between(500, 5000)).select("doc_id", "lang")


@query("SELECT c_custkey, c_name, c_mktsegment FROM customer")
def roundtrip_json(spark, d):
    return round_trip(_t(spark, d, "customer").select("c_custkey", "c_name", "c_mktsegment"), "json")


@query("SELECT p_partkey, p_name, p_size FROM part")
def roundtrip_csv(spark, d):
    return round_trip(_t(spark, d, "part").select("p_partkey", "p_name", "p_size"), "csv")


@query("SELECT doc_id FROM documents WHERE regexp_matches(text, 'password|token') AND source IN ('src1', 'src2', 'src3') AND lang IS NOT DISTINCT FROM 'en'")
def filter_docs(spark, d):
    return _t(spark, d, "documents").filter(F.col("text").rlike("password|token") & F.col("source").isin("src1", "src2", "src3") & F.col("lang").eqNullSafe("en")).select("doc_id")


@query("SELECT CASE WHEN n_chars < 500 THEN 'short' WHEN n_chars < 5000 THEN 'middle' ELSE 'long' END AS size, count(*) AS n FROM documents GROUP BY ALL")
def case_lengths(spark, d):
    size = F.when(F.col("n_chars") < 500, "short").when(F.col("n_chars") < 5000, "middle").otherwise("long")
    return _t(spark, d, "documents").groupBy(size.alias("size")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL")
def join_broadcast(spark, d):
    return _t(spark, d, "customer").join(F.broadcast(_t(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"))  # nation: 25 rows


@query("SELECT o_orderkey, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL")
def join_smj(spark, d):
    return _t(spark, d, "orders").join(_t(spark, d, "lineitem").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("lines"))


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)")
def join_semi(spark, d):
    return _t(spark, d, "documents").join(_t(spark, d, "labels").filter("toxic = 1"), "doc_id", "left_semi").select("doc_id")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark, d):
    return _t(spark, d, "documents").join(_t(spark, d, "labels"), "doc_id", "left_anti").select("doc_id")


@query(STATE + ", a AS (SELECT z AS topic, count(*) AS n FROM tz WHERE doc_id % 2 = 0 GROUP BY ALL), b AS (SELECT z AS topic, count(*) AS m FROM tz WHERE doc_id % 2 = 1 GROUP BY ALL) SELECT topic, coalesce(n, 0) - coalesce(m, 0) AS delta FROM a FULL JOIN b USING (topic)")
def join_full_delta(spark, d):
    tz = _state(spark, d)
    a, b = counts.count_topic(tz.filter("doc_id % 2 = 0")), counts.count_topic(tz.filter("doc_id % 2 = 1")).withColumnRenamed("n", "m")
    return a.join(b, "topic", "full").select("topic", (F.coalesce("n", F.lit(0)) - F.coalesce("m", F.lit(0))).alias("delta"))


@query("WITH b AS (SELECT i AS bucket, i * 50000.0 AS lo, (i + 1) * 50000.0 AS hi FROM range(12) t(i)) SELECT bucket, count(*) AS orders FROM orders JOIN b ON o_totalprice >= lo AND o_totalprice < hi GROUP BY ALL")
def join_range_bucket(spark, d):
    b = spark.range(12).select(F.col("id").alias("bucket"), (F.col("id") * 50000.0).alias("lo"), ((F.col("id") + 1) * 50000.0).alias("hi"))
    return _t(spark, d, "orders").join(F.broadcast(b), (F.col("o_totalprice") >= F.col("lo")) & (F.col("o_totalprice") < F.col("hi"))).groupBy("bucket").agg(F.count(F.lit(1)).alias("orders"))  # 12 rows


@query("WITH e AS (SELECT *, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS view_id FROM events) SELECT event_id, view_id FROM e WHERE event_type = 'click'")
def join_asof_click(spark, d):
    """Each click with the user's latest earlier view, by one sorted pass instead of a range join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    view = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return _t(spark, d, "events").withColumn("view_id", view).filter("event_type = 'click'").select("event_id", "view_id")


@query("SELECT c.event_id AS click_id, count(*) AS views FROM events c JOIN events v ON c.user_id = v.user_id AND v.event_type = 'view' AND v.ts BETWEEN c.ts - INTERVAL 6 HOURS AND c.ts WHERE c.event_type = 'click' GROUP BY ALL")
def join_interval_view_click(spark, d):
    e = _t(spark, d, "events")
    c = e.filter("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("ts").alias("at"))
    v = e.filter("event_type = 'view'").select("user_id", "ts")
    return c.join(v, "user_id").filter(F.col("ts").between(F.col("at") - F.expr("INTERVAL 6 HOURS"), F.col("at"))).groupBy("click_id").agg(F.count(F.lit(1)).alias("views"))


@query("SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
def agg_cube_lang_source(spark, d):
    return _t(spark, d, "documents").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT r_name, n_name, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name, c_mktsegment)")
def agg_rollup_geo(spark, d):
    c = _t(spark, d, "customer").join(_t(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(_t(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return c.rollup("r_name", "n_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT source, count_if(lang = 'en')::BIGINT AS en, count_if(lang = 'fr')::BIGINT AS fr, count_if(lang = 'de')::BIGINT AS de, count_if(lang = 'es')::BIGINT AS es FROM documents GROUP BY source")
def agg_pivot_source_lang(spark, d):
    langs = ["en", "fr", "de", "es"]
    return _t(spark, d, "documents").groupBy("source").pivot("lang", langs).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT user_id, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id")
def agg_distinct(spark, d):
    return _t(spark, d, "events").groupBy("user_id").agg(F.count_distinct("event_type").alias("kinds"))


@query("SELECT lang, quantile_cont(n_chars, 0.5)::DOUBLE AS p50, quantile_cont(n_chars, 0.9)::DOUBLE AS p90 FROM documents GROUP BY lang")
def agg_percentile(spark, d):
    return _t(spark, d, "documents").groupBy("lang").agg(F.percentile("n_chars", F.lit(0.5)).alias("p50"), F.percentile("n_chars", F.lit(0.9)).alias("p90"))


@query(STATE + " SELECT topic, word_id, n, row_number() OVER (PARTITION BY topic ORDER BY n DESC, word_id) AS rank FROM phi QUALIFY rank <= 10")
def topk_per_topic(spark, d):
    return measures.top_words(counts.count_word_topic(_state(spark, d)), 10)


@query(DOCTOK + " SELECT word, tf FROM wc ORDER BY tf DESC, word LIMIT 50")
def topk_words(spark, d):
    return prepare.word_counts(_doc_tokens(spark, d)).select("word", "tf").orderBy(F.desc("tf"), "word").limit(50)


@query(STATE + " SELECT topic, word_id, n, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr FROM phi WINDOW w AS (PARTITION BY topic ORDER BY n DESC)")
def win_topwords_rank(spark, d):
    w = Window.partitionBy("topic").orderBy(F.desc("n"))
    return counts.count_word_topic(_state(spark, d)).select("topic", "word_id", "n", F.rank().over(w).cast("bigint").alias("r"), F.dense_rank().over(w).cast("bigint").alias("dr"), F.round(F.percent_rank().over(w), 9).alias("pr"))


@query(STATE + " SELECT doc_id, topic, (sum(n) OVER (PARTITION BY doc_id ORDER BY topic))::BIGINT AS upto FROM theta")
def win_running_mass(spark, d):
    return counts.count_doc_topic(_state(spark, d)).select("doc_id", "topic", F.sum("n").over(Window.partitionBy("doc_id").orderBy("topic")).alias("upto"))


@query(STATE + " SELECT doc_id, topic, (sum(n) OVER (PARTITION BY doc_id ORDER BY topic ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))::BIGINT AS rest FROM theta")
def win_suffix_mass(spark, d):
    w = Window.partitionBy("doc_id").orderBy("topic").rowsBetween(0, Window.unboundedFollowing)
    return counts.count_doc_topic(_state(spark, d)).select("doc_id", "topic", F.sum("n").over(w).alias("rest"))


@query("SELECT conv_id, turn, role, lag(role) OVER w AS before, lead(role) OVER w AS after FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def win_lag_turns(spark, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return _t(spark, d, "conversations").select("conv_id", "turn", "role", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS near FROM (SELECT event_id, user_id, date_trunc('second', ts) AS ts FROM events)")
def win_range_events(spark, d):
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    return _t(spark, d, "events").withColumn("s", F.unix_timestamp(F.date_trunc("second", "ts"))).select("event_id", F.count(F.lit(1)).over(w).alias("near"))


@query(DOCTOK + ", en AS (SELECT DISTINCT word FROM t JOIN documents USING (doc_id) WHERE lang = 'en'), fr AS (SELECT DISTINCT word FROM t JOIN documents USING (doc_id) WHERE lang = 'fr') SELECT word FROM en INTERSECT SELECT word FROM fr")
def set_intersect_words(spark, d):
    t = _doc_tokens(spark, d).join(_t(spark, d, "documents").select("doc_id", "lang"), "doc_id")
    return t.filter("lang = 'en'").select("word").intersect(t.filter("lang = 'fr'").select("word"))


@query(DOCTOK + f" SELECT DISTINCT w AS word FROM (SELECT unnest({_SPLIT.format('text')}) AS w FROM conversations) EXCEPT SELECT word FROM wc")
def set_except_oov(spark, d):
    seen = _doc_tokens(spark, d).select("word")
    return _t(spark, d, "conversations").select(F.explode(words(F.col("text"))).alias("word")).subtract(seen)


@query(STATE + " SELECT topic, sum(n)::BIGINT AS n FROM (SELECT topic, n FROM psi UNION ALL SELECT topic, n FROM psi) GROUP BY topic")
def set_union_delta(spark, d):
    psi = counts.count_topic(_state(spark, d))
    return training.merge_totals(psi, psi)


@query("SELECT page_id, length(regexp_replace(regexp_replace(html, '<(script|style)[^>]*>.*?</(script|style)>', ' ', 'gs'), '<[^>]*>', ' ', 'g')) AS n FROM pages")
def str_html_text(spark, d):
    return _t(spark, d, "pages").select("page_id", F.length(strip_tags(F.col("html"))).cast("bigint").alias("n"))


@query("SELECT a.p_brand AS a, b.p_brand AS b, levenshtein(a.p_brand, b.p_brand) AS distance FROM (SELECT DISTINCT p_brand FROM part) a JOIN (SELECT DISTINCT p_brand FROM part) b ON a.p_brand < b.p_brand")
def str_typo_pairs(spark, d):
    x = _t(spark, d, "part").select(F.col("p_brand").alias("a")).distinct()
    return x.join(x.toDF("b"), F.col("a") < F.col("b")).select("a", "b", F.levenshtein("a", "b").cast("bigint").alias("distance"))


@query(f"SELECT conv_id, turn, len(list_distinct({_SPLIT.format('text')})) AS n FROM conversations")
def arr_bag_distinct(spark, d):
    return _t(spark, d, "conversations").select("conv_id", "turn", F.size(F.array_distinct(words(F.col("text")))).cast("bigint").alias("n"))


@query(STATE + " SELECT doc_id, count(*) AS topics, max(n) AS most FROM theta GROUP BY doc_id")
def map_doc_topics(spark, d):
    m = counts.count_doc_topic(_state(spark, d)).groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("topic", "n"))).alias("m"))
    return m.select("doc_id", F.size("m").cast("bigint").alias("topics"), F.array_max(F.map_values("m")).alias("most"))


@query("SELECT (props->>'$.k')::BIGINT AS k, count(*) AS n FROM events GROUP BY ALL")
def json_props_k(spark, d):
    return _t(spark, d, "events").groupBy(F.get_json_object("props", "$.k").cast("bigint").alias("k")).agg(F.count(F.lit(1)).alias("n"))


# --- streaming --------------------------------------------------------------------------------------


def _events_stream(spark, d):
    e = _t(spark, d, "events")
    return streams.replay(spark, f"{d}/events.parquet*", e.schema)


@query("SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def stream_tumbling_events(spark, d):
    return streams.drained(streams.tumbling(_events_stream(spark, d)), "tumbling", "complete")


@query("SELECT start, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS start FROM events) GROUP BY ALL")
def stream_sliding_events(spark, d):
    return streams.drained(streams.sliding(_events_stream(spark, d)), "sliding", "complete")


@query("WITH e AS (SELECT user_id, ts, (ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 30 MINUTES)::INT AS fresh FROM events), g AS (SELECT user_id, ts, sum(coalesce(fresh, 1)) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM e) SELECT user_id, min(ts) AS start, count(*) AS n FROM g GROUP BY user_id, k")
def stream_session_users(spark, d):
    return streams.drained(streams.sessions(_events_stream(spark, d)), "sessions", "complete")


@query("SELECT user_id, count(*) AS n FROM (SELECT DISTINCT user_id, event_type FROM events) GROUP BY user_id")
def stream_dedupe(spark, d):
    one = streams.drained(streams.unique_queries(_events_stream(spark, d).select("user_id", "event_type", "ts"), ["user_id", "event_type"], "3650 days"), "dedupe")
    return one.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT user_id, count(*) AS events, round(sum(value), 4) AS value FROM events GROUP BY user_id")
def stream_user_profile(spark, d):
    s = _events_stream(spark, d).groupBy("user_id").agg(F.count(F.lit(1)).alias("events"), F.round(F.sum("value"), 4).alias("value"))
    return streams.drained(s, "profiles", "complete")
