"""Further queries of the catalogue: workloads over other example sets, reports, sources, baselines and stream joins."""

from __future__ import annotations

from pyspark.sql import functions as F

from evalengine.functions import lexical, surface
from evalengine.operators import judge, measures, reports
from evalengine.plans.catalogue import COMMON, F1, INSTRUCT, MODELS, SAID, TOK, U, answered, query, rounded, said, tokenised
from evalengine.plans.spec import EvaluationSpec, MetricSpec
from evalengine.responders import local, simulated
from evalengine.sources import paged as pages
from evalengine.sources import tables
from evalengine.sources.staging import shared_folder, staged
from evalengine.streaming import evaluation as streaming


# Workloads.


SUMMARISE = f"""WITH s AS (SELECT CAST(doc_id AS VARCHAR) AS example_id, string_split(text, chr(10))[1] AS reference FROM documents), r AS (SELECT *, {said(*MODELS[0])} AS response FROM s),
tok AS (SELECT *, {TOK('response')} AS a, {TOK('reference')} AS b FROM r)"""


@query(SUMMARISE + f" SELECT example_id, round({F1('a', 'b')}, 6) AS f1, CAST(contains(lower(response), lower(reference)) AS DOUBLE) AS holds FROM tok")
def summarise_scores(spark, d):
    rows = tables.summarise(spark, d).withColumn("response", simulated.respond(*MODELS[0], F.col("example_id"), F.col("reference")))
    rows = rows.withColumns({"a": lexical.tokens(F.col("response")), "b": lexical.tokens(F.col("reference"))})
    return rounded(rows.select("example_id", lexical.token_f1(F.col("a"), F.col("b")).alias("f1"), lexical.contains(F.col("response"), F.col("reference"), case=False).alias("holds")))


@query()
def summarise_overlap(spark, d):
    """ROUGE-L and BLEU of the summaries."""
    rows = tables.summarise(spark, d).withColumn("response", simulated.respond(*MODELS[0], F.col("example_id"), F.col("reference")))
    rows = rows.withColumns({"a": lexical.tokens(F.col("response")), "b": lexical.tokens(F.col("reference"))})
    return rounded(rows.select("example_id", lexical.rouge_l("a", "b").alias("rouge_l"), lexical.sentence_bleu(F.col("a"), F.col("b")).alias("bleu")))


@query(f"""WITH qa AS (SELECT CAST(item_id AS VARCHAR) AS example_id, array_to_string(string_split(text, ' ')[9:], ' ') AS reference FROM benchmark), r AS (SELECT *, {said(*MODELS[0])} AS response FROM qa),
tok AS (SELECT *, {TOK('response')} AS a, {TOK('reference')} AS b FROM r)
SELECT example_id, CAST(array_to_string(a, ' ') = array_to_string(b, ' ') AS DOUBLE) AS exact, CAST(contains(response, reference) AS DOUBLE) AS holds, round({F1('a', 'b')}, 6) AS f1 FROM tok""")
def factual_scores(spark, d):
    """Exact match, containment and token F1 of the question set."""
    rows = tables.factqa(spark, d).withColumn("response", simulated.respond(*MODELS[0], F.col("example_id"), F.col("reference")))
    rows = rows.withColumns({"a": lexical.tokens(F.col("response")), "b": lexical.tokens(F.col("reference"))})
    return rounded(rows.select("example_id", lexical.exact_match(F.col("response"), F.col("reference")).alias("exact"), lexical.contains(F.col("response"), F.col("reference")).alias("holds"), lexical.token_f1(F.col("a"), F.col("b")).alias("f1")))


@query(SAID + f""", f AS (SELECT conv_id, turn, {F1('a', 'b')} AS f1 FROM tok), r AS (SELECT *, avg(f1) OVER (PARTITION BY conv_id ORDER BY turn ROWS UNBOUNDED PRECEDING) AS running FROM f)
SELECT conv_id, count(f1) AS turns, round(avg(f1), 6) AS mean, round(min(f1), 6) AS worst, round(arg_max(f1, turn), 6) AS last, round(min(running), 6) AS lowest_running FROM r GROUP BY 1""")
def thread_answer_scores(spark, d):
    turns = tokenised(spark, d).select("conv_id", "turn", lexical.token_f1(F.col("a"), F.col("b")).alias("f1"))
    return rounded(reports.thread_scores(turns, "conv_id", "turn", "f1"))


JUDGE_PROMPT = "'Grade the answer.' || chr(10) || 'Criterion: ' || criterion || '. Scale: 1 to 5.' || chr(10) || 'Instruction: ' || instruction || chr(10) || 'Answer: ' || response || chr(10) || 'Give a score and an explanation.'"
GRADED = SAID + f""", p AS (SELECT *, {F1('a', 'b')} AS f1, {JUDGE_PROMPT} AS prompt FROM tok, (VALUES ('helpfulness'), ('accuracy')) AS c(criterion)),
k AS (SELECT *, sha256(length(prompt) || ':' || prompt || '7:judge-a15:simulated-judge3:0.03:256') AS cache_key FROM p),
m AS (SELECT cache_key, min(reference) AS reference FROM k GROUP BY 1), kk AS (SELECT k.example_id, k.criterion, k.cache_key, k.a, {TOK('m.reference')} AS b FROM k JOIN m USING (cache_key)),
g AS (SELECT example_id, criterion, {F1('a', 'b')} AS f1, {U("'judge:' || cache_key")} AS u FROM kk),
s AS (SELECT example_id, criterion, CASE WHEN u >= 0.01 THEN CAST(greatest(1, least(5, CAST(floor(1 + 4 * f1 + (u - 0.5) + 0.5) AS INTEGER))) AS DOUBLE) END AS score FROM g)"""


def _graded(spark, d):
    from evalengine.plans.runner import grade

    spec = EvaluationSpec("graded", (MetricSpec("judge", "judge", "ordinal"),))
    return grade(answered(spark, d), spec, {"criteria": ["helpfulness", "accuracy"]})


@query(GRADED + " SELECT example_id, criterion, score FROM s")
def judge_by_calls(spark, d):
    """Every verdict is a call to a grader: distinct prompts, lanes, retries; scores parsed from its text."""
    return _graded(spark, d).select("example_id", "criterion", "score")


@query(GRADED + " SELECT criterion, count(*) AS verdicts, count(*) FILTER (score IS NULL) AS unparsed, round(avg(score), 6) AS mean FROM s GROUP BY 1")
def judge_criteria(spark, d):
    held = staged(_graded(spark, d))
    lost = judge.unparsed(held).groupBy("criterion").agg(F.count("*").alias("unparsed"))
    return rounded(held.groupBy("criterion").agg(F.count("*").alias("verdicts"), F.avg("score").alias("mean")).join(lost, "criterion", "left").fillna(0, ["unparsed"]))


# Sources, sinks, reports.


@query("SELECT p_partkey AS id, CAST(p_partkey // 128 AS INTEGER) AS page, p_name AS body FROM part")
def paged_source(spark, d):
    """The parts as a listing of 128 keys to a page."""
    return pages.listed(tables.table(spark, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_name").alias("body")), 128)


@query("SELECT d.doc_id, d.lang FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")
def labelled_documents(spark, d):
    return reports.labelled(tables.table(spark, d, "documents").select("doc_id", "lang"), tables.table(spark, d, "labels"), "doc_id")


@query("""SELECT CASE WHEN b.i IS NULL THEN 'only_a' WHEN a.i IS NULL THEN 'only_b' ELSE 'both' END AS side, count(*) AS ids
FROM (SELECT DISTINCT doc_id AS i FROM labels) a FULL OUTER JOIN (SELECT DISTINCT vec_id AS i FROM embeddings) b ON a.i = b.i GROUP BY 1""")
def run_alignment(spark, d):
    return reports.alignment(tables.table(spark, d, "labels").select(F.col("doc_id").alias("i")), tables.table(spark, d, "embeddings").select(F.col("vec_id").alias("i")), "i")


@query("(SELECT 'common' AS kind, doc_id AS i FROM labels INTERSECT SELECT 'common', vec_id FROM embeddings) UNION ALL (SELECT 'gap', doc_id FROM documents EXCEPT ALL SELECT 'gap', vec_id FROM embeddings)")
def run_common_and_gap(spark, d):
    ids = lambda t, c: tables.table(spark, d, t).select(F.col(c).alias("i"))
    both = reports.common(ids("labels", "doc_id"), ids("embeddings", "vec_id"), "i").select(F.lit("common").alias("kind"), "i")
    return both.unionAll(reports.gap(ids("documents", "doc_id"), ids("embeddings", "vec_id"), "i").select(F.lit("gap").alias("kind"), "i"))


@query(f"""WITH {INSTRUCT}, f AS (SELECT conv_id, len({TOK(said(*MODELS[0]))}) AS x, len({TOK(said(*MODELS[1]))}) AS y FROM instruct)
SELECT conv_id, count(*) AS n_a, count(*) AS n_b, round(avg(x) - avg(y), 6) AS gap FROM f GROUP BY 1""")
def paired_threads(spark, d):
    """Two models' answer lengths of a thread, met by cogroup."""
    run = lambda m: tokenised(spark, d, m).select("conv_id", F.size("a").cast("double").alias("words"))
    return rounded(reports.paired_groups(run(0), run(1), "conv_id", "words"))


TWO = f"WITH {INSTRUCT}, w AS (SELECT example_id, conv_id, turn, {F1(TOK(said(*MODELS[0])), TOK('reference'))} AS a, {F1(TOK(said(*MODELS[1])), TOK('reference'))} AS b FROM instruct)"


def _two(spark, d):
    one = lambda m, c: tokenised(spark, d, m).select("example_id", "turn", lexical.token_f1(F.col("a"), F.col("b")).alias(c))
    return one(0, "a").join(one(1, "b").drop("turn"), "example_id")


@query(TWO + " SELECT turn, round(avg(a), 6) AS a, round(avg(b), 6) AS b FROM w GROUP BY 1")
def metric_matrix(spark, d):
    """Unpivoted to long rows, then pivoted to turn by model."""
    rows = reports.long(_two(spark, d), ["example_id", "turn"], ["a", "b"])
    return rounded(reports.matrix(rows, "turn", "metric", "value", ["a", "b"]))


@query(TWO + ", l AS (SELECT example_id, turn, 'a' AS metric, a AS value FROM w UNION ALL SELECT example_id, turn, 'b', b FROM w) SELECT example_id, metric, round(value, 6) AS value, rank() OVER p AS rank, dense_rank() OVER p AS dense, round(cume_dist() OVER p, 6) AS quarter_share, round(percent_rank() OVER p, 6) AS percent FROM l WINDOW p AS (PARTITION BY metric, turn ORDER BY round(value, 9) DESC)")
def leaderboard(spark, d):
    rows = reports.long(_two(spark, d), ["example_id", "turn"], ["a", "b"]).withColumn("value", F.round("value", 9))
    return rounded(reports.leaderboard(rows, ["metric", "turn"], "value").drop("turn"))


@query("""SELECT conv_id, turn, lag(length(text)) OVER w AS before, lead(length(text)) OVER w AS after, first_value(length(text)) OVER f AS first, nth_value(length(text), 2) OVER f AS second
FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn), f AS (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def turn_trend(spark, d):
    rows = reports.trend(tables.table(spark, d, "conversations"), "conv_id", "turn", F.length("text").cast("long"))
    return rows.select("conv_id", "turn", "before", "after", "first", "second")


@query("SELECT doc_id, quality FROM labels WHERE toxic = 1")
def report_partitioned(spark, d):
    """Written by a partition column; the filter reads that folder alone."""
    rows = tables.table(spark, d, "labels").select("doc_id", "quality", "toxic")
    return reports.written(rows, shared_folder(spark, "report"), ["toxic"]).where("toxic = 1").select("doc_id", "quality")


@query("SELECT source, count(*) AS docs, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY 1")
def report_exports(spark, d):
    """Stored as JSON lines and as CSV, read from both, and summed by a view over the two."""
    rows = tables.table(spark, d, "documents").groupBy("source", "lang").agg(F.count("*").alias("docs"), F.sum("n_chars").alias("chars"))
    reports.views({"json_report": reports.written(rows, shared_folder(spark, "json"), fmt="json"), "csv_report": reports.written(rows, shared_folder(spark, "csv"), fmt="csv")})
    return spark.sql("SELECT j.source, CAST(sum(j.docs) AS BIGINT) AS docs, CAST(sum(c.chars) AS BIGINT) AS chars FROM json_report j JOIN csv_report c ON j.source <=> c.source AND j.lang <=> c.lang GROUP BY 1")


@query(SAID + f" SELECT example_id, CAST(array_to_string(a, ' ') = array_to_string(b, ' ') AS DOUBLE) AS exact, round({F1('a', 'b')}, 6) AS f1, CAST(contains(response, reference) AS DOUBLE) AS holds FROM tok")
def metrics_in_sql(spark, d):
    surface.install(spark)
    reports.views({"answers": answered(spark, d)})
    return spark.sql("SELECT example_id, eval_exact_match(response, reference) AS exact, round(eval_token_f1(response, reference), 6) AS f1, eval_contains(response, reference) AS holds FROM answers")


@query(SAID + f" SELECT example_id, CAST({COMMON('a', 'b')} AS INTEGER) AS shared FROM tok")
def bag_overlap(spark, d):
    return tokenised(spark, d).select("example_id", surface.overlap(surface.bag(F.col("a")), surface.bag(F.col("b"))).alias("shared"))


@query("SELECT count(*) AS rows, count(*) FILTER (text IS NULL OR text = '') AS empty, CAST(sum(length(text)) AS BIGINT) AS chars FROM documents")
def observed_counters(spark, d):
    """Counters of a write, taken while it runs."""
    rows, seen = reports.observed(tables.table(spark, d, "documents"), "documents", rows=F.count(F.lit(1)), empty=F.count_if(F.col("text").isNull() | (F.col("text") == "")), chars=F.sum(F.length("text")).cast("long"))
    staged(rows.select("doc_id", "text"))
    got = seen.get
    return spark.createDataFrame([(got["rows"], got["empty"], got["chars"])], "rows long, empty long, chars long")


@query("SELECT count(DISTINCT text) AS exact, true AS approximate_near, true AS sketched_near FROM documents")
def distinct_prompts(spark, d):
    return reports.distinct_prompts(tables.table(spark, d, "documents"), "text")


@query("""WITH s AS (SELECT count(value) AS n, avg(value) AS m FROM events), c AS (SELECT avg((value - m) ** 2) AS m2, avg((value - m) ** 3) AS m3, avg((value - m) ** 4) AS m4 FROM events, s)
SELECT n, round(m3 / m2 ** 1.5, 6) AS skew, round(m4 / m2 ** 2 - 3, 6) AS excess_kurtosis, round(2 * sqrt(6.0::DOUBLE / n), 6) AS skew_limit, round(2 * sqrt(24.0::DOUBLE / n), 6) AS kurtosis_limit FROM c, s""")
def moment_diagnostics(spark, d):
    return rounded(reports.moment_diagnostics(tables.table(spark, d, "events"), "value"))


@query("SELECT 0 AS position, 'render' AS stage, true AS timed UNION ALL SELECT 1, 'respond', true UNION ALL SELECT 2, 'score', true")
def stage_timings(spark, d):
    t = reports.Timings()
    rows = t.stage("render", lambda: staged(tables.instruct(spark, d)))
    said_ = t.stage("respond", lambda: staged(rows.withColumn("response", simulated.respond(*MODELS[0], F.col("example_id"), F.col("reference")))))
    t.stage("score", lambda: said_.agg(F.avg(lexical.exact_match(F.col("response"), F.col("reference")))).first())
    return t.table(spark).select("position", "stage", ((F.col("seconds") > 0) & (F.col("share") <= 1)).alias("timed"))


@query("SELECT event_type, round(1 - (sum(value * 8 + 200) / 1000) / (epoch(max(ts)) - epoch(min(ts))), 4) AS overhead FROM events GROUP BY 1")
def overhead_by_type(spark, d):
    """Share of the log's span in which calls of a type were not at work, had they run one after the other."""
    at = F.unix_micros(F.col("ts").cast("timestamp")) / 1e6
    runs = tables.table(spark, d, "events").groupBy("event_type").agg((F.sum(F.col("value") * 8 + 200) / 1000).alias("ideal"), (F.max(at) - F.min(at)).alias("total"))
    return rounded(measures.overhead(runs, F.col("ideal"), F.col("total")).select("event_type", "overhead"), 4)


@query("SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS minute, count(*) AS calls FROM events GROUP BY 1")
def calls_in_flight(spark, d):
    """Calls that touch each hour of the log; a call of no length touches one."""
    log = tables.table(spark, d, "events").select((F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).alias("start_s")).withColumn("end_s", F.col("start_s"))
    return measures.inflight(log, width=3600)


# Baselines and local models.


@query(f"{SAID} SELECT example_id, sha256(response) AS digest FROM said")
def row_udf_baseline(spark, d):
    """The simulated model one Python call a row: the answers of the batched and of the native form, at a row's price."""
    name, quality = MODELS[0]

    def say(key: str, reference: str) -> str:
        from evalengine.responders.base import Request
        from evalengine.responders.simulated import SimulatedResponder

        return SimulatedResponder(name, quality).answer(Request(key, "", reference)).text

    rows = surface.row_wise(tables.instruct(spark, d), say, "response", "example_id", "reference")
    return rows.select("example_id", F.sha2("response", 256).alias("digest"))


@query(f"WITH {INSTRUCT} SELECT count(*) AS examples, true AS one_open_a_batch, true AS one_open_a_worker FROM instruct")
def uncached_responder_baseline(spark, d):
    """How often a responder is opened: for every batch of ten without the pool, at most once in a worker with it."""
    import pandas as pd

    from evalengine.responders import base

    spec = {"provider": "simulated", "model": MODELS[0][0], "quality": MODELS[0][1]}

    def opens(batches):
        for frame in batches:
            held, fresh = base.OPENED["count"], 0
            for k in range(0, len(frame), 10):
                own = base.responder_for(spec)
                own.open()
                fresh += 1
                for key, reference in zip(frame["example_id"][k : k + 10], frame["reference"][k : k + 10], strict=True):
                    asked = base.Request(key, "", reference)
                    if own.answer(asked).text != base.pooled(spec).answer(asked).text:
                        raise AssertionError("the pool changed an answer")
                own.close()
            yield pd.DataFrame({"rows": [len(frame)], "fresh": [fresh], "pooled": [base.OPENED["count"] - held]})

    found = tables.instruct(spark, d).select("example_id", "reference").mapInPandas(opens, "rows long, fresh long, pooled long")
    return found.agg(F.sum("rows").alias("examples"), (F.sum("fresh") >= F.sum("rows") / 10).alias("one_open_a_batch"), (F.max("pooled") <= 1).alias("one_open_a_worker"))


@query("SELECT CAST(item_id AS VARCHAR) AS example_id, CAST(true AS BOOLEAN) AS right FROM benchmark")
def local_model(spark, d):
    """A retrieval model that each worker holds answers the question set in whole batches; asked its own prompts it is right."""
    import tempfile

    from evalengine.operators.inference import CallPolicy, call_model, keyed

    rows = tables.factqa(spark, d).select("example_id", F.concat_ws(" ", "question", "reference").alias("prompt"), "reference")
    known = rows.select("prompt", "reference").orderBy("example_id").limit(10_000).collect()
    base = spark.conf.get("spark.checkpoint.dir", None)
    folder = base.removeprefix("file://").removeprefix("file:") if base else tempfile.mkdtemp(prefix="evalengine-")
    path = local.remember(f"{folder}/retrieval.npz", [r.prompt for r in known], [r.reference for r in known])
    model = {"provider": "local", "model": "retrieval", "path": path}
    asked = keyed(rows, model)
    replies = staged(call_model(asked.dropDuplicates(["cache_key"]), model, CallPolicy(lanes=2, whole_batches=True)))
    return asked.join(replies, "cache_key").select("example_id", (F.col("response_text") == F.col("reference")).alias("right"))


# Streams.


@query("SELECT e.event_id, e.user_id, c.c_mktsegment AS segment FROM events e JOIN customer c ON c.c_custkey = e.user_id")
def stream_static_join(spark, d):
    stream = streaming.source(spark, d, "events")
    known = tables.table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("segment"))
    return streaming.to_end(streaming.attached(stream.select("event_id", "user_id"), known, "user_id"), "append")


@query("SELECT a.event_id AS request, b.event_id AS response FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def stream_interval_join(spark, d):
    """Two streams: a view and the clicks of the same user within six hours."""
    asked = streaming.source(spark, d, "events").where("event_type = 'view'").select(F.col("event_id").alias("request"), "user_id", "ts")
    told = streaming.source(spark, d, "events").where("event_type = 'click'").select(F.col("event_id").alias("response"), "user_id", "ts")
    return streaming.to_end(streaming.matched(asked, told, "user_id", "6 hours").select("request", "response"), "append")


@query("SELECT user_id, count(*) AS calls, CAST(sum(ceil(value)) AS BIGINT) AS spent FROM events GROUP BY 1")
def stream_lane_state(spark, d):
    """A limiter's books kept by lane in a stream: calls and tokens so far."""
    log = streaming.source(spark, d, "events").select("user_id", F.ceil("value").cast("long").alias("tokens"))
    return streaming.to_end(streaming.lane_state(log, "user_id", "tokens"), "update").groupBy("user_id").agg(F.max("calls").alias("calls"), F.max("spent").alias("spent"))


@query("""WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS fresh FROM events), g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e)
SELECT user_id, min(ts) AS start, count(*) AS calls FROM g GROUP BY user_id, s""")
def stream_sessions(spark, d):
    out = streaming.to_end(streaming.sessions(streaming.source(spark, d, "events"), "12 hours"))
    return out.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "calls")


@query("SELECT count(DISTINCT user_id || '/' || event_type) AS keys FROM events")
def stream_dedup(spark, d):
    stream = streaming.source(spark, d, "events").withColumn("k", F.concat_ws("/", "user_id", "event_type"))
    return streaming.to_end(streaming.distinct_requests(stream.select("k", "ts"), "k", late="400 days"), "append").agg(F.count("*").alias("keys"))
