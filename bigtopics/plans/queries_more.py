"""Registered queries: joins, strings, user functions and streams that the other modules lack."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from ..functions.text import words
from ..operators import counts, placement, predict
from ..sources.files import scratch, settle
from ..streaming import streams
from .queries import _SPLIT, _U, ALPHA, BETA, DOCTOK, STATE, TOK, TOPICS, _doc_tokens, _model, _state, _t, _tokens, query


@query(STATE + " SELECT a.topic AS a, b.topic AS b, count(*) AS docs FROM theta a JOIN theta b ON a.doc_id = b.doc_id AND a.topic < b.topic GROUP BY ALL")
def join_theta_pairs(spark, d):
    """Baskets in which two topics meet; a basket has few topics, so the self-join grows with the baskets."""
    theta = settle(counts.count_doc_topic(_state(spark, d)), "theta")
    b = theta.select("doc_id", F.col("topic").alias("b"))
    return theta.select("doc_id", F.col("topic").alias("a")).join(b, "doc_id").filter("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("docs"))


@query(f"SELECT conv_id, turn, len({_SPLIT.format('text')}) AS n, md5(array_to_string({_SPLIT.format('text')}, ' ')) AS digest FROM conversations")
def str_tokens(spark, d):
    own = words(F.col("text"))
    return _t(spark, d, "conversations").select("conv_id", "turn", F.size(own).cast("bigint").alias("n"), F.md5(F.concat_ws(" ", own).cast("binary")).alias("digest"))


_LANGS = ("de", "en", "es", "fr")


@query(DOCTOK + f", l AS (SELECT CAST(floor({_U.format(chr(39) + '7|0|' + chr(39) + ' || doc_id || ' + chr(39) + '|' + chr(39) + ' || pos')} * {TOPICS}) AS INTEGER) AS topic, lang FROM t JOIN documents USING (doc_id)) SELECT topic, " + ", ".join(f"count_if(lang = '{x}')::BIGINT AS {x}" for x in _LANGS) + " FROM l GROUP BY topic")
def agg_pivot_topic_lang(spark, d):
    labelled = counts.init_topics(_doc_tokens(spark, d), TOPICS).groupBy("doc_id", F.col("z").alias("topic")).agg(F.count(F.lit(1)).alias("n"))
    wide = labelled.join(_t(spark, d, "documents").select("doc_id", "lang"), "doc_id").groupBy("topic").pivot("lang", list(_LANGS)).agg(F.sum("n"))
    return wide.select("topic", *(F.coalesce(F.col(x), F.lit(0)).cast("bigint").alias(x) for x in _LANGS))


@query(STATE + " SELECT doc_id, round(-sum(n / s * ln(n / s)) + 0.0, 6) AS entropy FROM (SELECT *, sum(n) OVER (PARTITION BY doc_id) AS s FROM theta) GROUP BY doc_id")
def udf_entropy(spark, d):
    @F.pandas_udf("double")
    def entropy(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in parts:
            p = [np.asarray(x, float) / np.sum(x) for x in s]
            yield pd.Series([float(-(q * np.log(q)).sum()) for q in p], dtype="float64")

    rows = counts.count_doc_topic(_state(spark, d)).groupBy("doc_id").agg(F.collect_list("n").alias("n"))
    return rows.select("doc_id", (F.round(entropy("n"), 6) + 0.0).alias("entropy"))


@query("WITH s AS (SELECT lang, n_chars % 100 AS score, toxic AS y FROM documents JOIN labels USING (doc_id)), r AS (SELECT lang, y, (rank() OVER (PARTITION BY lang ORDER BY score) + (count(*) OVER (PARTITION BY lang, score) - 1) / 2) AS rk FROM s) SELECT lang, CASE WHEN sum(y) * count_if(y = 0) > 0 THEN round((sum(rk * y) - sum(y) * (sum(y) + 1) / 2) / (sum(y) * count_if(y = 0)), 6) END AS auc FROM r GROUP BY lang")
def udaf_auc(spark, d):
    """AUC of each language by a grouped-aggregate function; a group is one language's labelled rows."""

    @F.pandas_udf("double")
    def auc(score: pd.Series, y: pd.Series) -> float:
        up, down = int(y.sum()), int((y == 0).sum())
        return None if not up * down else float((score.rank()[y == 1].sum() - up * (up + 1) / 2) / (up * down))

    s = _t(spark, d, "documents").join(_t(spark, d, "labels"), "doc_id").select("lang", (F.col("n_chars") % 100).alias("score"), F.col("toxic").alias("y"))
    return s.groupBy("lang").agg(auc("score", "y").alias("auc")).select("lang", F.round("auc", 6).alias("auc"))


@query(TOK + ", n AS (SELECT doc_id, count(*) * 8 AS bytes FROM tok GROUP BY doc_id) SELECT doc_id, unnest(range(0, bytes, 32)) // 32 AS packet, least(32, bytes - unnest(range(0, bytes, 32))) AS bytes FROM n")
def udtf_packets(spark, d):
    """Packets of at most 32 bytes of each basket, emitted by a table function."""

    class Packets:
        def eval(self, doc_id: int, size: int):
            for k in range(-(-size // 32)):
                yield doc_id, k, min(32, size - 32 * k)

    spark.udtf.register("packets_of", F.udtf(Packets, returnType="doc_id bigint, packet bigint, bytes bigint"))
    _tokens(spark, d).groupBy("doc_id").agg((F.count(F.lit(1)) * 8).alias("size")).createOrReplaceTempView("basket_sizes")
    return spark.sql("SELECT p.doc_id, p.packet, p.bytes FROM basket_sizes, LATERAL packets_of(basket_sizes.doc_id, basket_sizes.size) p")


@query(STATE + f" SELECT (SELECT count(*) * 4 FROM tz) AS label_bytes, (SELECT count(*) * 8 FROM theta) AS sparse_theta_bytes, (SELECT count(DISTINCT doc_id) * {TOPICS} * 4 FROM tok) AS dense_theta_bytes")
def state_bytes(spark, d):
    """Memory of labels alone beside stored document-topic counts: 4 bytes a label, 8 an entry, 4 a dense cell."""
    theta = counts.count_doc_topic(_state(spark, d))
    per = theta.groupBy("doc_id").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("topics"))
    return per.agg((F.sum("n") * 4).alias("label_bytes"), (F.sum("topics") * 8).alias("sparse_theta_bytes"), (F.count(F.lit(1)) * TOPICS * 4).alias("dense_theta_bytes"))


@query(STATE + ", w AS (SELECT word_id % 4 AS shard, count(*) * 8 AS bytes FROM phi GROUP BY ALL) SELECT shard, bytes, bytes <= 1000000 AS fits FROM w")
def shard_fits(spark, d):
    phi = counts.count_word_topic(_state(spark, d))
    return placement.check_shard_size(phi.withColumn("shard", F.col("word_id") % 4), 1_000_000, refuse=False)


_HALF = "(SELECT (epoch_us(min(ts)) + epoch_us(max(ts))) // 2 FROM events)"


@query(f"SELECT date_trunc('hour', ts) AS start, count(*) AS n FROM events WHERE epoch_us(ts) >= {_HALF} GROUP BY ALL")
def stream_late_drop(spark, d):
    """Hourly counts of a stream whose older half comes after its newer one: the watermark has passed it, so it is dropped.

    A micro-batch drops what was late before its predecessor, so the newer half comes in two.
    """
    e = _t(spark, d, "events").select(F.col("ts").cast("timestamp").alias("ts"))
    us = F.unix_micros("ts")
    half = e.agg(F.floor((F.min(us) + F.max(us)) / 2).alias("h")).first().h
    folder = scratch(spark, "late")
    for k, part in enumerate(((us >= half) & (us % 2 == 0), (us >= half) & (us % 2 != 0), us < half)):  # one file each, in this order
        e.filter(part).coalesce(1).write.parquet(f"{folder}/part={k}")
    source = spark.readStream.schema("ts timestamp, part int").option("maxFilesPerTrigger", 1).parquet(folder)
    hourly = source.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")
    got = streams.updated(hourly, "late-drop")
    return got.groupBy("start").agg(F.max("n").alias("n"))


@query()
def stream_predict(spark, d):
    """Topics of a stream of baskets by the batch predictor, micro-batch by micro-batch; equals the batch (tested)."""
    _, _, phi, psi, alpha, v = _model(spark, d)
    q = settle(predict.packed_queries(_tokens(spark, d), phi, predict.best_prior_topic(phi, psi, alpha, BETA, v)), "queries")
    totals = [r.n for r in psi.orderBy("topic").collect()]
    folder = scratch(spark, "asked")
    q.repartition(3).write.parquet(folder)
    asked = spark.readStream.schema(q.schema).option("maxFilesPerTrigger", 1).parquet(folder)
    return streams.predict_stream(asked, lambda batch: predict.predict(batch, totals, [ALPHA] * TOPICS, BETA, v))
