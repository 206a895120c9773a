"""Registered queries of the topic-model engine, each with its SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.rand import uniform
from ..functions.text import words
from ..operators import baselines, clicks, counts, dedup, measures, pipeline_model, placement, predict, prepare, prior, retrieval, sampling
from ..sources import corpora
from ..sources.files import settle
from . import training

TOPICS, ALPHA, BETA = 8, 0.1, 0.01

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return keep


# --- shared inputs ----------------------------------------------------------------------------------

_U = "('0x' || substr(md5({0}), 1, 8))::BIGINT / 4294967296.0"
TOK = """WITH tok AS (SELECT l_orderkey AS doc_id, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate) - 1 AS pos, l_partkey AS word_id FROM lineitem)"""
STATE = (
    TOK
    + f""", tz AS (SELECT *, CAST(floor({_U.format("'7|0|' || doc_id || '|' || pos")} * {TOPICS}) AS INTEGER) AS z FROM tok),
theta AS (SELECT doc_id, z AS topic, count(*) AS n FROM tz GROUP BY ALL), phi AS (SELECT word_id, z AS topic, count(*) AS n FROM tz GROUP BY ALL),
psi AS (SELECT z AS topic, count(*) AS n FROM tz GROUP BY ALL), alpha AS (SELECT topic, {ALPHA}::DOUBLE AS alpha FROM psi), v AS (SELECT count(DISTINCT word_id) AS v FROM tok)"""
)
_SPLIT = "list_filter(string_split_regex(lower(coalesce({0}, '')), '[^\\p{{L}}]+'), lambda w: w <> '')"
DOCTOK = f"WITH dt AS (SELECT doc_id, unnest(list_zip(w, range(len(w)))) AS x FROM (SELECT doc_id, {_SPLIT.format('text')} AS w FROM documents)), t AS (SELECT doc_id, x[2] AS pos, x[1] AS word FROM dt), wc AS (SELECT word, count(*) AS tf, count(DISTINCT doc_id) AS df FROM t GROUP BY word)"
SENT = f"WITH sp AS (SELECT doc_id, lang, unnest(list_zip(p, range(len(p)))) AS x FROM (SELECT doc_id, lang, string_split_regex(coalesce(text, ''), '[.\\n]') AS p FROM documents)), sq AS (SELECT doc_id * 1048576 + x[2] AS query_id, doc_id, x[2]::BIGINT AS sentence, lang, {_SPLIT.format('x[1]')} AS words FROM sp), s AS (SELECT * FROM sq WHERE len(words) > 0)"


def _t(spark: SparkSession, d: str, name: str) -> DataFrame:
    return corpora.table(spark, d, name)


def _tokens(spark, d):
    return corpora.baskets(_t(spark, d, "lineitem"))


def _state(spark, d):
    return counts.init_topics(_tokens(spark, d), TOPICS)


def _model(spark, d):
    tz = _state(spark, d)
    theta, phi, psi = counts.count_doc_topic(tz), counts.count_word_topic(tz), counts.count_topic(tz)
    return tz, theta, phi, psi, counts.flat_alpha(psi, ALPHA), _vocab_size(tz)


def _vocab_size(tokens: DataFrame) -> int:
    return tokens.select("word_id").distinct().count()


def _doc_tokens(spark, d):
    return prepare.tokenize(_t(spark, d, "documents"), "doc_id", "text")


def _sentences(spark, d):
    return corpora.query_id(corpora.sentences(_t(spark, d, "documents")))


# --- corpora and preparation ------------------------------------------------------------------------


@query(DOCTOK + " SELECT doc_id, count(*) AS n FROM t GROUP BY doc_id")
def tok_counts(spark, d):
    return _doc_tokens(spark, d).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))


@query(DOCTOK + " SELECT word, tf, df FROM wc")
def word_freq(spark, d):
    return prepare.word_counts(_doc_tokens(spark, d))


@query(DOCTOK + " SELECT doc_id, count(*) AS n FROM t JOIN wc USING (word) WHERE df >= 2 GROUP BY doc_id")
def drop_rare(spark, d):
    t = _doc_tokens(spark, d)
    return prepare.drop_rare(t, prepare.word_counts(t), min_df=2).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))


@query(DOCTOK + " SELECT doc_id, count(*) AS n FROM t WHERE word NOT IN (SELECT word FROM wc ORDER BY tf DESC, word LIMIT 20) GROUP BY doc_id")
def drop_common(spark, d):
    t = _doc_tokens(spark, d)
    return prepare.drop_common(t, prepare.common_words(prepare.word_counts(t), top_n=20)).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))


@query(DOCTOK + " SELECT word FROM wc WHERE df > 0.2 * (SELECT count(DISTINCT doc_id) FROM t)")
def common_by_documents(spark, d):
    t = _doc_tokens(spark, d)
    return prepare.common_words(prepare.word_counts(t), max_df_ratio=0.2, docs=t.select("doc_id").distinct().count())


@query(SENT + " SELECT min(query_id) AS query_id FROM s GROUP BY array_to_string(words, ' ')")
def dedupe_queries(spark, d):
    return prepare.dedupe_queries(_sentences(spark, d)).select("query_id")


@query(SENT + " SELECT min(query_id) AS query_id FROM s GROUP BY array_to_string(list_sort(words), ' ')")
def dedupe_query_bags(spark, d):
    return prepare.dedupe_queries(_sentences(spark, d), "bag").select("query_id")


@query(SENT + " SELECT len(words)::BIGINT AS size, count(*) AS n FROM s WHERE len(words) >= 2 GROUP BY ALL")
def drop_single(spark, d):
    return prepare.drop_short(_sentences(spark, d)).groupBy(F.size("words").cast("bigint").alias("size")).agg(F.count(F.lit(1)).alias("n"))


@query(
    SENT
    + """, e AS (SELECT query_id, unnest(list_zip(words, range(len(words)))) AS x FROM s), t AS (SELECT query_id, x[2] AS pos, x[1] AS word FROM e),
c AS (SELECT word, count(*) AS tf FROM t GROUP BY word), r AS (SELECT t.* FROM t JOIN c USING (word) WHERE tf >= 2),
u AS (SELECT * FROM r WHERE word NOT IN (SELECT word FROM c ORDER BY tf DESC, word LIMIT 20)),
q AS (SELECT query_id, list(word ORDER BY pos) AS w FROM u GROUP BY query_id), k AS (SELECT min(query_id) AS query_id, any_value(len(w)) AS n FROM q GROUP BY array_to_string(w, ' '))
SELECT 1::BIGINT AS step, 'tokenise' AS name, count(DISTINCT query_id) AS queries, count(*) AS tokens FROM t UNION ALL SELECT 2, 'rare', count(DISTINCT query_id), count(*) FROM r
UNION ALL SELECT 3, 'common', count(DISTINCT query_id), count(*) FROM u UNION ALL SELECT 4, 'duplicates', count(*), sum(n)::BIGINT FROM k UNION ALL SELECT 5, 'short', count(*), sum(n)::BIGINT FROM k WHERE n >= 2"""
)
def prep_audit(spark, d):
    return prepare.prepare_corpus(_sentences(spark, d).select("query_id", "words"))[1]


@query(DOCTOK + " SELECT word, row_number() OVER (ORDER BY tf DESC, word) - 1 AS word_id, tf, df FROM wc")
def vocab_ids(spark, d):
    return prepare.build_vocab(prepare.word_counts(_doc_tokens(spark, d)))


@query(DOCTOK + ", vo AS (SELECT word, row_number() OVER (ORDER BY tf DESC, word) - 1 AS word_id FROM wc WHERE df >= 2) SELECT doc_id, count(*) AS n, sum(word_id)::BIGINT AS ids FROM t JOIN vo USING (word) GROUP BY doc_id")
def encoded(spark, d):
    t = _doc_tokens(spark, d)
    vocab = prepare.build_vocab(prepare.word_counts(t).filter("df >= 2"))
    return prepare.encode(t, vocab).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"), F.sum("word_id").alias("ids"))


@query(STATE + " SELECT doc_id, pos, word_id, z FROM tz")
def packed_roundtrip(spark, d):
    return prepare.unpack(prepare.pack(_state(spark, d)))


@query(TOK + " SELECT count(DISTINCT doc_id) AS docs, count(DISTINCT word_id) AS words, count(*) AS tokens, round(count(*) / count(DISTINCT doc_id), 6) AS avg_len FROM tok")
def corpus_stats(spark, d):
    return prepare.corpus_stats(_tokens(spark, d))


@query(TOK + f" SELECT DISTINCT doc_id, CASE WHEN {_U.format(chr(39) + '7|' + chr(39) + ' || doc_id')} < 0.1 THEN 'test' ELSE 'train' END AS part FROM tok")
def holdout_split(spark, d):
    return prepare.split_holdout(_tokens(spark, d).select("doc_id").distinct(), "doc_id")


@query(TOK + ", l AS (SELECT doc_id, count(*) AS len FROM tok GROUP BY doc_id), c AS (SELECT len, count(*) AS n FROM l GROUP BY len), g AS (SELECT len, least(20, floor((sum(n) OVER (ORDER BY len) - n / 2) * 20 / sum(n) OVER ()) + 1)::BIGINT AS grp FROM c) SELECT grp, count(*) AS docs FROM l JOIN g USING (len) GROUP BY grp")
def length_groups(spark, d):
    length = _tokens(spark, d).groupBy("doc_id").agg(F.count(F.lit(1)).alias("len"))
    return prepare.split_holdout(length, "doc_id", length_col="len").groupBy("grp").agg(F.count(F.lit(1)).alias("docs"))


@query(SENT + " SELECT query_id, len(words)::BIGINT AS n FROM s")
def sentence_corpus(spark, d):
    return _sentences(spark, d).select("query_id", F.size("words").cast("bigint").alias("n"))


@query(TOK + " SELECT doc_id, pos, word_id FROM tok")
def basket_corpus(spark, d):
    return _tokens(spark, d)


@query(TOK + " SELECT p_brand AS word, count(*) AS n FROM tok JOIN part ON word_id = p_partkey GROUP BY ALL")
def coarse_corpus(spark, d):
    return corpora.coarse_baskets(_t(spark, d, "lineitem"), _t(spark, d, "part")).groupBy("word").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT conv_id, turn, len({_SPLIT.format('text')})::BIGINT AS n FROM conversations WHERE role = 'user'")
def turn_corpus(spark, d):
    return corpora.turns(_t(spark, d, "conversations")).select("conv_id", "turn", F.size("words").cast("bigint").alias("n"))


@query("SELECT user_id, event_type AS word, count(*) AS n FROM events GROUP BY ALL")
def event_corpus(spark, d):
    return corpora.event_bags(_t(spark, d, "events")).groupBy("user_id", "word").agg(F.count(F.lit(1)).alias("n"))


# --- counts and objective ---------------------------------------------------------------------------


@query(STATE + " SELECT * FROM theta")
def theta_counts(spark, d):
    return counts.count_doc_topic(_state(spark, d))


@query(STATE + " SELECT * FROM phi")
def phi_counts(spark, d):
    return counts.count_word_topic(_state(spark, d))


@query(STATE + " SELECT * FROM psi")
def psi_counts(spark, d):
    return counts.count_topic(_state(spark, d))


@query(STATE + " SELECT 'theta' AS kind, doc_id AS id, topic, n FROM theta UNION ALL SELECT 'phi', word_id, topic, n FROM phi UNION ALL SELECT 'psi', -1, topic, n FROM psi")
def agg_grouping_sets(spark, d):
    return counts.all_counts(_state(spark, d)).withColumn("id", F.col("id").cast("bigint"))


@query(STATE + f" SELECT doc_id, topic, round((n + {ALPHA}) / (sum(n) OVER (PARTITION BY doc_id) + {ALPHA} * {TOPICS}), 9) AS p FROM theta")
def theta_prob(spark, d):
    _, theta, _, _, alpha, _ = _model(spark, d)
    return counts.doc_topic_prob(theta, alpha).withColumn("p", F.round("p", 9))


@query(STATE + f" SELECT word_id, topic, round((phi.n + {BETA}) / (psi.n + v * {BETA}), 9) AS p, round({BETA} / (psi.n + v * {BETA}), 12) AS background FROM phi JOIN psi USING (topic), v")
def phi_prob(spark, d):
    _, _, phi, psi, _, v = _model(spark, d)
    return counts.word_topic_prob(phi, psi, BETA, v).select("word_id", "topic", F.round("p", 9).alias("p"), F.round("background", 12).alias("background"))


@query(STATE + f", len AS (SELECT doc_id, sum(n) AS n FROM theta GROUP BY doc_id) SELECT round((SELECT sum(lgamma(n + {ALPHA}) - lgamma({ALPHA})) FROM theta) - (SELECT sum(lgamma(n + {ALPHA * TOPICS}) - lgamma({ALPHA * TOPICS})) FROM len) + (SELECT sum(lgamma(n + {BETA}) - lgamma({BETA})) FROM phi) - (SELECT sum(lgamma(n + v * {BETA}) - lgamma(v * {BETA})) FROM psi, v), 4) AS ll")
def joint_ll(spark, d):
    tz = _state(spark, d)
    return counts.joint_log_likelihood(tz, ALPHA, BETA, TOPICS, _vocab_size(tz))


@query(STATE + f", r AS (SELECT word_id, count(*) AS e FROM phi GROUP BY word_id) SELECT word_id % 4 AS shard, count(*) AS words, sum(e)::BIGINT AS entries, (sum(e) * 8 + count(*) * 8)::BIGINT AS bytes, count(*) * {4 * TOPICS} AS dense_bytes FROM r GROUP BY ALL")
def phi_sparsity(spark, d):
    return counts.model_footprint(counts.count_word_topic(_state(spark, d)), 4, TOPICS)


@query(STATE + " SELECT doc_id, pos, word_id, z FROM tz")
def init_topics(spark, d):
    return _state(spark, d)


@query(STATE + ", p AS (SELECT topic, n / sum(n) OVER (PARTITION BY topic) AS p FROM theta) SELECT topic, round(-sum(p * ln(p)), 6) AS entropy FROM p GROUP BY topic")
def math_entropy_topics(spark, d):
    return counts.topic_shares(counts.count_doc_topic(_state(spark, d)))


# --- samplers ---------------------------------------------------------------------------------------

_CELLS = ", cell AS (SELECT tz.doc_id, tz.pos, tz.word_id, psi.topic, coalesce(theta.n, 0) - (psi.topic = z)::INT AS th, coalesce(phi.n, 0) - (psi.topic = z)::INT AS f, psi.n - (psi.topic = z)::INT AS total FROM tz CROSS JOIN psi LEFT JOIN theta ON theta.doc_id = tz.doc_id AND theta.topic = psi.topic LEFT JOIN phi ON phi.word_id = tz.word_id AND phi.topic = psi.topic)"


@query(STATE + _CELLS + f" SELECT doc_id, pos, round(sum({ALPHA} * {BETA} / (total + v * {BETA})), 9) AS prior_mass, round(sum(th * {BETA} / (total + v * {BETA})), 9) AS doc_mass, round(sum(({ALPHA} + th) * f / (total + v * {BETA})), 9) AS word_mass FROM cell, v GROUP BY doc_id, pos")
def bucket_masses(spark, d):
    tz, theta, phi, psi, _, v = _model(spark, d)
    return sampling.bucket_masses(tz, theta, phi, psi, ALPHA, BETA, v).select("doc_id", "pos", *(F.round(c, 9).alias(c) for c in ("prior_mass", "doc_mass", "word_mass")))


@query(STATE + _CELLS + f" SELECT doc_id, pos, round(sum(({ALPHA} + th) * ({BETA} + f) / (total + v * {BETA})), 8) AS mass FROM cell, v GROUP BY doc_id, pos")
def dense_conditional(spark, d):
    tz, theta, phi, psi, _, v = _model(spark, d)
    return sampling.bucket_masses(tz, theta, phi, psi, ALPHA, BETA, v).select("doc_id", "pos", F.round(F.col("prior_mass") + F.col("doc_mass") + F.col("word_mass"), 8).alias("mass"))


SWEEP = _CELLS + f", w AS (SELECT doc_id, pos, word_id, topic, ({ALPHA} + th) * ({BETA} + f) / (total + v * {BETA}) AS w FROM cell, v), c AS (SELECT doc_id, pos, word_id, topic, sum(w) OVER (PARTITION BY doc_id, pos ORDER BY topic ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto, sum(w) OVER (PARTITION BY doc_id, pos) AS whole FROM w), nz AS (SELECT doc_id, pos, word_id, min(topic) AS z FROM c WHERE upto > {_U.format(chr(39) + '7|1|' + chr(39) + ' || doc_id || ' + chr(39) + '|' + chr(39) + ' || pos')} * whole OR topic = {TOPICS - 1} GROUP BY ALL)"


@query(STATE + SWEEP + " SELECT doc_id, pos, word_id, z FROM nz")
def snapshot_sweep(spark, d):
    tz, theta, phi, psi, _, v = _model(spark, d)
    return sampling.snapshot_sweep(tz, theta, phi, psi, TOPICS, ALPHA, BETA, v)


@query(STATE + SWEEP + " SELECT count(*) AS tokens, count_if(nz.z <> tz.z)::BIGINT AS changed FROM nz JOIN tz USING (doc_id, pos)")
def changed_fraction(spark, d):
    new = snapshot_sweep(spark, d).select("doc_id", "pos", F.col("z").alias("new"))
    return _state(spark, d).join(new, ["doc_id", "pos"]).agg(F.count(F.lit(1)).alias("tokens"), F.count_if(F.col("z") != F.col("new")).alias("changed"))


# --- distribution -----------------------------------------------------------------------------------

_DS = f"floor({_U.format(chr(39) + '7|doc|' + chr(39) + ' || doc_id')} * 4)::BIGINT"
_WS = f"floor({_U.format(chr(39) + '7|word|' + chr(39) + ' || word_id')} * 4)::BIGINT"
BLOCKS = TOK + f", b AS (SELECT *, {_DS} AS doc_shard, {_WS} AS word_shard FROM tok)"


def _blocks(spark, d):
    return _tokens(spark, d).withColumn("doc_shard", placement.doc_shard(4)).withColumn("word_shard", placement.word_shard(4))


def _word_tf(spark, d):
    return _tokens(spark, d).groupBy("word_id").agg(F.count(F.lit(1)).alias("tf"))


@query(BLOCKS + " SELECT word_shard, count(DISTINCT word_id) AS words, count(*) AS tokens FROM b GROUP BY word_shard")
def shard_sizes(spark, d):
    per = _blocks(spark, d).groupBy("word_shard", "word_id").agg(F.count(F.lit(1)).alias("n"))
    return per.groupBy("word_shard").agg(F.count(F.lit(1)).alias("words"), F.sum("n").alias("tokens"))


@query(BLOCKS + " SELECT doc_shard, word_shard, count(*) AS tokens FROM b GROUP BY ALL")
def block_grid(spark, d):
    return _blocks(spark, d).groupBy("doc_shard", "word_shard").agg(F.count(F.lit(1)).alias("tokens"))


_BALANCE = "count(*) AS shards, round(max(load) / avg(load), 6) AS max_over_mean, round(stddev_pop(load) / avg(load), 6) AS cv, round(1 - avg(load) / max(load), 6) AS idle_share"


@query(BLOCKS + f", l AS (SELECT doc_shard, word_shard, count(*) AS load FROM b GROUP BY ALL) SELECT {_BALANCE} FROM l")
def block_balance(spark, d):
    return placement.balance_report(block_grid(spark, d).withColumnRenamed("tokens", "load"))


@query(BLOCKS + f", l AS (SELECT word_shard, count(*) AS load FROM b GROUP BY ALL) SELECT {_BALANCE} FROM l")
def shard_balance(spark, d):
    return placement.balance_report(_blocks(spark, d).groupBy("word_shard").agg(F.count(F.lit(1)).alias("load")))


_RANKED = ", r AS (SELECT word_id, count(*) AS tf, row_number() OVER (ORDER BY count(*) DESC, word_id) - 1 AS k FROM tok GROUP BY word_id)"


@query(TOK + _RANKED + " SELECT word_id, tf, (CASE WHEN (k // 4) % 2 = 1 THEN 3 - k % 4 ELSE k % 4 END)::BIGINT AS word_shard FROM r")
def word_shards_snake(spark, d):
    return placement.assign_words(_word_tf(spark, d), 4, "snake")


@query(TOK + _RANKED + " SELECT word_id, tf, (k % 4)::BIGINT AS word_shard FROM r")
def word_shards_rank(spark, d):
    return placement.assign_words(_word_tf(spark, d), 4, "rank")


@query(
    TOK.replace("WITH tok", "WITH RECURSIVE tok")
    + _RANKED.replace("row_number() OVER (ORDER BY count(*) DESC, word_id) - 1", "row_number() OVER (ORDER BY count(*) DESC, word_id)")
    + """, g AS (SELECT 0::BIGINT AS k, 0::BIGINT AS word_id, 0::BIGINT AS shard, [0::BIGINT, 0, 0, 0] AS loads
UNION ALL SELECT r.k, r.word_id, list_position(g.loads, list_min(g.loads)) - 1, list_transform(g.loads, lambda x, i: CASE WHEN i = list_position(g.loads, list_min(g.loads)) THEN x + r.tf ELSE x END) FROM g JOIN r ON r.k = g.k + 1)
SELECT g.word_id, r.tf, g.shard::BIGINT AS word_shard FROM g JOIN r USING (k)"""
)
def word_shards_weighted(spark, d):
    return placement.assign_words(_word_tf(spark, d), 4, "weighted")


@query(BLOCKS + " SELECT DISTINCT (doc_shard - word_shard + 4) % 4 AS step, doc_shard, word_shard FROM b")
def diagonal_schedule(spark, d):
    """The step of each block that holds tokens."""
    return placement.schedule_of(_blocks(spark, d), 4)


_B6 = BLOCKS.replace("* 4)", "* 6)") + ", plan AS (SELECT DISTINCT (doc_shard - word_shard + 6) % 6 AS step, doc_shard, word_shard FROM b)"


@query(_B6 + " SELECT x.step, x.doc_shard AS d1, x.word_shard AS w1, y.doc_shard AS d2, y.word_shard AS w2 FROM plan x JOIN plan y ON x.step = y.step AND ((x.doc_shard = y.doc_shard AND x.word_shard < y.word_shard) OR (x.word_shard = y.word_shard AND x.doc_shard < y.doc_shard))")
def schedule_conflicts(spark, d):
    """Blocks of one step of the schedule of all baskets that share a shard: none."""
    t = _tokens(spark, d).select(placement.doc_shard(6).alias("doc_shard"), placement.word_shard(6).alias("word_shard"))
    return placement.conflicts(placement.schedule_of(t, 6))


@query(TOK + f" SELECT floor({_U.format(chr(39) + '7|segment|' + chr(39) + ' || doc_id')} * 3)::BIGINT AS segment, count(DISTINCT doc_id) AS docs, count(*) AS tokens FROM tok GROUP BY ALL")
def segment_sizes(spark, d):
    per = _tokens(spark, d).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))
    return per.groupBy(F.floor(uniform(F.lit("segment"), "doc_id") * 3).cast("bigint").alias("segment")).agg(F.count(F.lit(1)).alias("docs"), F.sum("n").alias("tokens"))


@query(STATE + SWEEP + " SELECT doc_id, pos, word_id, z FROM nz")
def z_diff_apply(spark, d):
    tz, theta, phi, psi, _, v = _model(spark, d)
    new = sampling.snapshot_sweep(tz, theta, phi, psi, TOPICS, ALPHA, BETA, v)
    changed = new.join(tz.select("doc_id", "pos", F.col("z").alias("old")), ["doc_id", "pos"]).filter("z <> old")
    return training.apply_diffs(tz, changed)


def _two_configs(spark, d):
    """Labels before and after a sweep in which each half of the documents saw only its own changes."""
    return _state(spark, d), snapshot_sweep(spark, d)


@query(STATE + SWEEP + " SELECT word_id, z AS topic, count(*) AS n FROM nz GROUP BY ALL")
def phi_delta_merge(spark, d):
    old, new = _two_configs(spark, d)
    cfg = F.col("doc_id") % 2
    deltas = counts.count_word_topic(new.filter(cfg == 0)).unionByName(counts.count_word_topic(new.filter(cfg == 1))).unionByName(counts.count_word_topic(old).withColumn("n", -F.col("n")))
    return training.merge_models(counts.count_word_topic(old), deltas)


@query(STATE + SWEEP + " SELECT z AS topic, count(*) AS n FROM nz GROUP BY ALL")
def psi_merge(spark, d):
    old, new = _two_configs(spark, d)
    deltas = counts.count_topic(new).unionByName(counts.count_topic(old).withColumn("n", -F.col("n")))
    return training.merge_totals(counts.count_topic(old), deltas)


@query()
def free_schedule(spark, d):
    costs = {(r.doc_shard, r.word_shard): float(r.tokens) for r in block_grid(spark, d).collect()}
    return spark.createDataFrame(placement.schedule_free(costs, 4, 1, 3), "worker bigint, doc_shard bigint, word_shard bigint, begun double, ended double")


@query()
def visit_balance(spark, d):
    return free_schedule(spark, d).groupBy("doc_shard", "word_shard").agg(F.count(F.lit(1)).alias("visits"))


@query(TOK + ", b AS (SELECT doc_id % 4 AS block, doc_id, count(*) * 8 AS bytes FROM tok GROUP BY ALL), p AS (SELECT block, floor((sum(bytes) OVER (PARTITION BY block ORDER BY doc_id) - bytes) / 1024)::BIGINT AS packet, bytes FROM b) SELECT block, packet, count(*) AS docs, sum(bytes)::BIGINT AS bytes FROM p GROUP BY ALL")
def packet_counts(spark, d):
    t = _tokens(spark, d).withColumn("block", F.col("doc_id") % 4)
    return pipeline_model.packetise(t, 1024).groupBy("block", "packet").agg(F.count(F.lit(1)).alias("docs"), F.sum("bytes").alias("bytes"))


def _link(spark, d) -> pipeline_model.Link:
    """The fitted link with the messages of all baskets as its volume."""
    return pipeline_model.Link(volume=float(pipeline_model.volume_kb(_tokens(spark, d))))


_CURVE = "in_flight, packet_kb FROM (VALUES " + ", ".join(f"({t}::BIGINT, {kb}::BIGINT, {m}::DOUBLE)" for t, kb, m in pipeline_model.PUBLISHED) + ") c(in_flight, packet_kb, published)"
_VOLUME = "(SELECT ceil(sum(bytes) / 1000.0) AS kb FROM (SELECT l_orderkey, count(*) * 8 AS bytes FROM lineitem GROUP BY l_orderkey))"
_MINUTES = "(2593.0::DOUBLE + 7.2e-6::DOUBLE * (kb / packet_kb) + 1.9::DOUBLE * (kb / packet_kb) / pow(in_flight, 1.5)) / 60"


@query(f"SELECT published, round({_MINUTES}, 4) AS modelled, {_CURVE}, {_VOLUME}")
def pipeline_grid(spark, d):
    """Modelled minutes of the messages of all baskets along the buffer curve, beside the published ones (of another corpus)."""
    return pipeline_model.pipeline_grid(spark, _link(spark, d))


@query(f"SELECT {_MINUTES} AS minutes, {_CURVE}, {_VOLUME}")
def buffer_curve(spark, d):
    """Minutes for the messages of all baskets by packet size, with as many in flight as the buffer holds."""
    link = _link(spark, d)
    rows = [(kb, *pipeline_model.tune_buffer(200_000, (kb,), link)[::2]) for kb in (1, 10, 100, 1000, 5000, 10_000, 20_000, 200_000)]
    return spark.createDataFrame(rows, "packet_kb bigint, in_flight bigint, minutes double")


# --- prior ------------------------------------------------------------------------------------------


@query(TOK + ", l AS (SELECT doc_id, count(*) AS len FROM tok GROUP BY doc_id) SELECT len, count(*) AS n_docs FROM l GROUP BY len")
def len_hist(spark, d):
    return prior.length_histogram(_tokens(spark, d))


@query(STATE + " SELECT topic, n, count(*) AS n_docs FROM theta GROUP BY ALL")
def omega_hist(spark, d):
    return prior.topic_doc_histogram(counts.count_doc_topic(_state(spark, d)))


@query(STATE + f", len AS (SELECT doc_id, sum(n)::BIGINT AS n FROM theta GROUP BY doc_id), below AS (SELECT sum(list_sum(list_transform(range(n), lambda j: 1 / ({ALPHA * TOPICS} + j)))) AS b FROM len), above AS (SELECT topic, sum(list_sum(list_transform(range(n), lambda j: 1 / ({ALPHA} + j)))) AS a FROM theta GROUP BY topic) SELECT topic, round({ALPHA} * a / b, 9) AS alpha FROM above, below")
def alpha_step(spark, d):
    tz, theta, _, _, alpha, _ = _model(spark, d)
    return prior.alpha_step(alpha, prior.topic_doc_histogram(theta), prior.length_histogram(tz)).withColumn("alpha", F.round("alpha", 9))


# --- prediction -------------------------------------------------------------------------------------

_RBEST = f", cand AS (SELECT w.word_id, psi.topic, (coalesce(phi.n, 0) + {BETA}) / (psi.n + v * {BETA}) * {ALPHA} AS score FROM (SELECT DISTINCT word_id FROM phi) w CROSS JOIN psi CROSS JOIN v LEFT JOIN phi ON phi.word_id = w.word_id AND phi.topic = psi.topic), rb AS (SELECT word_id, topic AS best_topic, score AS best_score FROM cand QUALIFY row_number() OVER (PARTITION BY word_id ORDER BY score DESC, topic) = 1)"


@query(STATE + _RBEST + " SELECT word_id, best_topic, round(best_score, 12) AS best_score FROM rb")
def r_best(spark, d):
    _, _, phi, psi, alpha, v = _model(spark, d)
    return predict.best_prior_topic(phi, psi, alpha, BETA, v).withColumn("best_score", F.round("best_score", 12))


_TRAINED: dict[tuple[str, str], tuple[DataFrame, DataFrame, int]] = {}


def _trained_model(spark, d):
    """phi, psi and vocabulary size after three iterations of the grid on nine tenths of the baskets; written once for a session and folder."""
    key = (spark.sparkContext.applicationId, d)
    if key not in _TRAINED:
        tokens = _tokens(spark, d)
        v = _vocab_size(tokens)
        seen = settle(tokens.filter(uniform("doc_id") >= 0.1), "seen")
        model = training.GridTrainer(spark, training.Settings(topics=TOPICS, vocab_size=v, shards=8)).start(seen).train(3).model()
        _TRAINED[key] = (*(settle(x, "trained") for x in model), v)
    return _TRAINED[key]


def _predicted(spark, d, method, **options):
    """Topics of all baskets by a model trained on nine tenths of them; the others are new to it."""
    phi, psi, v = _trained_model(spark, d)
    q = predict.packed_queries(_tokens(spark, d), phi, predict.best_prior_topic(phi, psi, counts.flat_alpha(psi, ALPHA), BETA, v))
    totals = [0] * TOPICS
    for r in psi.collect():  # K rows
        totals[r.topic] = r.n
    return predict.predict(q, totals, [ALPHA] * TOPICS, BETA, v, method=method, **options)


@query()
def predict_greedy(spark, d):
    return _predicted(spark, d, "pruned")


@query()
def predict_full_scan(spark, d):
    return _predicted(spark, d, "full")


@query()
def predict_sampling(spark, d):
    return _predicted(spark, d, "sampling").withColumn("n", F.round("n", 6))


@query()
def predict_trials(spark, d):
    return _predicted(spark, d, "pruned", trials=3).withColumn("n", F.round("n", 6))


@query(STATE + ", tr AS (SELECT doc_id, topic % 2 AS trial, topic, n / sum(n) OVER (PARTITION BY doc_id, topic % 2) AS p FROM theta), k AS (SELECT doc_id, count(DISTINCT trial) AS t FROM tr GROUP BY doc_id) SELECT doc_id, topic, round(sum(p) / any_value(t), 9) AS p FROM tr JOIN k USING (doc_id) GROUP BY doc_id, topic")
def trial_average(spark, d):
    from pyspark.sql import Window

    theta = counts.count_doc_topic(_state(spark, d)).withColumn("trial", F.col("topic") % 2)
    return predict.trial_average(theta.withColumn("p", F.col("n") / F.sum("n").over(Window.partitionBy("doc_id", "trial"))))


@query(STATE + f" SELECT doc_id, topic, round((n + {ALPHA}) / (sum(n) OVER (PARTITION BY doc_id) + {ALPHA} * {TOPICS}), 6) AS p FROM theta WHERE doc_id % 10 = 0")
def query_theta(spark, d):
    _, theta, _, _, alpha, _ = _model(spark, d)
    return counts.doc_topic_prob(theta.filter("doc_id % 10 = 0"), alpha).withColumn("p", F.round("p", 6))


@query()
def query_theta_all(spark, d):
    """query_theta of every basket; the query with SQL has the ids divisible by 10."""
    _, theta, _, _, alpha, _ = _model(spark, d)
    return counts.doc_topic_prob(theta, alpha).withColumn("p", F.round("p", 6))


@query(TOK + _RANKED + ", b AS (SELECT unnest([640, 6400, 64000])::BIGINT AS budget) SELECT budget, count(k) AS pinned, round(coalesce(sum(tf), 0) / (SELECT sum(tf) FROM r), 6) AS hit_ratio FROM b LEFT JOIN r ON (k + 1) * 64 <= budget GROUP BY budget")
def cache_hit_curve(spark, d):
    return predict.cache_curve(_word_tf(spark, d), [640, 6400, 64000])


@query(STATE + _RBEST + " SELECT best_topic AS topic, count(*) AS words FROM rb GROUP BY ALL")
def pruned_topic_share(spark, d):
    return r_best(spark, d).groupBy(F.col("best_topic").alias("topic")).agg(F.count(F.lit(1)).alias("words"))


# --- topic de-duplication ---------------------------------------------------------------------------

_PAIRS = ", share AS (SELECT word_id, topic, phi.n / psi.n AS p FROM phi JOIN psi USING (topic)), l1 AS (SELECT x.topic AS a, y.topic AS b, round(2 - 2 * sum(least(x.p, y.p)), 6) AS l1, round(sum(least(x.p, y.p)), 6) AS sim FROM share x JOIN share y ON x.word_id = y.word_id AND x.topic < y.topic GROUP BY ALL)"
TAU = 0.58


@query(STATE + ", k AS (SELECT topic, n, sum(n) OVER (ORDER BY n DESC, topic) - n AS before, sum(n) OVER () AS whole FROM psi) SELECT topic, n::DOUBLE AS alpha, before < 0.9 * whole AS kept FROM k")
def prior_prune(spark, d):
    return dedup.prune_by_prior(counts.count_topic(_state(spark, d)).select("topic", F.col("n").cast("double").alias("alpha")), keep_mass=0.9)


def _topics(spark, d):
    """phi and psi, written once."""
    phi = settle(counts.count_word_topic(_state(spark, d)), "phi")
    return phi, settle(phi.groupBy("topic").agg(F.sum("n").alias("n")), "psi")


@query(STATE + _PAIRS + " SELECT * FROM l1")
def topic_l1_pairs(spark, d):
    _, _, phi, psi, _, _ = _model(spark, d)
    return dedup.topic_l1(phi, psi)


@query(STATE + f", sm AS (SELECT w.word_id, psi.topic, (coalesce(phi.n, 0) + {BETA}) / (psi.n + v * {BETA}) AS p FROM (SELECT DISTINCT word_id FROM phi) w CROSS JOIN psi CROSS JOIN v LEFT JOIN phi ON phi.word_id = w.word_id AND phi.topic = psi.topic) SELECT x.topic AS a, y.topic AS b, round(sum(abs(x.p - y.p)), 6) AS l1 FROM sm x JOIN sm y ON x.word_id = y.word_id AND x.topic < y.topic GROUP BY ALL")
def topic_l1_smoothed(spark, d):
    _, _, phi, psi, _, v = _model(spark, d)
    return dedup.topic_l1_smoothed(phi, psi, BETA, v)


@query(STATE + _PAIRS + f" SELECT * FROM l1 WHERE l1 < {TAU}")
def topic_pairs_below(spark, d):
    _, _, phi, psi, _, _ = _model(spark, d)
    return dedup.similar_topics(phi, psi, TAU)


@query()
def topic_pairs_minhash(spark, d):
    _, _, phi, psi, _, _ = _model(spark, d)
    return dedup.similar_topics_minhash(phi, psi, TAU)


_CLUSTER = STATE.replace("WITH tok", "WITH RECURSIVE tok") + _PAIRS + f", e AS (SELECT a, b FROM l1 WHERE l1 < {TAU} UNION SELECT b, a FROM l1 WHERE l1 < {TAU}), reach AS (SELECT topic, topic AS r FROM psi UNION SELECT reach.topic, e.b FROM reach JOIN e ON e.a = reach.r), cl AS (SELECT topic, min(r) AS cluster FROM reach GROUP BY topic)"


@query(_CLUSTER + " SELECT topic, cluster FROM cl")
def topic_clusters(spark, d):
    _, _, phi, psi, _, _ = _model(spark, d)
    return dedup.cluster_topics(psi, dedup.similar_topics(phi, psi, TAU))


@query(_CLUSTER + " SELECT word_id, cluster AS topic, sum(n)::BIGINT AS n FROM phi JOIN cl USING (topic) GROUP BY ALL")
def merged_phi(spark, d):
    phi, psi = _topics(spark, d)
    return dedup.merge_topics(phi, dedup.cluster_topics(psi, dedup.similar_topics(phi, psi, TAU)))


@query(STATE + _PAIRS + f", e AS (SELECT a AS t FROM l1 WHERE l1 < {TAU} UNION SELECT b FROM l1 WHERE l1 < {TAU}) SELECT count(*) AS duplicated, round(count(*) / {TOPICS}, 6) AS share FROM e")
def duplicate_share(spark, d):
    phi, psi = _topics(spark, d)
    return dedup.duplicate_share(dedup.similar_topics(phi, psi, TAU), TOPICS)


@query(STATE + _PAIRS + ", t AS (SELECT unnest([0.1, 0.5, 0.58, 0.6, 1.0])::DOUBLE AS tau) SELECT tau, round(1 - tau / 2, 6) AS sim, count(a) AS pairs, (SELECT count(DISTINCT x) FROM (SELECT a AS x FROM l1 WHERE l1 < tau UNION SELECT b FROM l1 WHERE l1 < tau)) AS topics_touched FROM t LEFT JOIN l1 ON l1 < tau GROUP BY tau")
def dedup_sweep(spark, d):
    return dedup.sweep_threshold(topic_l1_pairs(spark, d), [0.1, 0.5, 0.58, 0.6, 1.0])


_DILUTION = ", side AS (SELECT 'split' AS model, doc_id, topic, n FROM theta UNION ALL SELECT 'merged', doc_id, CASE WHEN topic < 3 THEN 0 ELSE topic END, sum(n) FROM theta GROUP BY ALL), lead AS (SELECT *, n / sum(n) OVER (PARTITION BY model, doc_id) AS share FROM side QUALIFY row_number() OVER (PARTITION BY model, doc_id ORDER BY n DESC, topic) = 1)"


@query(STATE + _DILUTION + " SELECT model, topic, count(*) AS queries, round(avg(share), 6) AS share FROM lead GROUP BY model, topic")
def dilution(spark, d):
    """The leading topic of each basket and its share, with the first three topics as copies of one and with them merged: copies lead less often than the topic they split."""
    theta = counts.count_doc_topic(_state(spark, d))
    merged = theta.groupBy("doc_id", F.when(F.col("topic") < 3, 0).otherwise(F.col("topic")).alias("topic")).agg(F.sum("n").alias("n"))

    def leading(t: DataFrame, name: str) -> DataFrame:
        best = t.groupBy("doc_id").agg(F.max(F.struct("n", (-F.col("topic")).alias("t"))).alias("b"), F.sum("n").alias("len"))
        lead = best.select((-F.col("b.t")).cast("int").alias("topic"), (F.col("b.n") / F.col("len")).alias("share"))
        return lead.groupBy(F.lit(name).alias("model"), "topic").agg(F.count(F.lit(1)).alias("queries"), F.round(F.avg("share"), 6).alias("share"))

    return leading(theta, "split").union(leading(merged, "merged"))
