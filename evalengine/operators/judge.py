"""Grading by a model: prompts, verdict parsing, pairwise preference, and the retrieval metrics."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from evalengine.functions.distributions import uniform

RUBRIC = "{rubric}\nCriterion: {criterion}. Scale: {low} to {high}.\nInstruction: "
NUMBER = r"(-?[0-9]+(?:\.[0-9]+)?)"


def grade_prompts(df: DataFrame, rubric: str, criteria: list[str], scale: tuple[int, int] = (1, 5)) -> DataFrame:
    """A row and a prompt for each example and criterion; they go through the same cached inference as any prompt."""
    crossed = df.withColumn("criterion", F.explode(F.array(*map(F.lit, criteria))))
    head = F.concat(F.lit(f"{rubric}\nCriterion: "), F.col("criterion"), F.lit(f". Scale: {scale[0]} to {scale[1]}.\nInstruction: "))
    return crossed.withColumn("prompt", F.concat(head, F.coalesce("instruction", F.lit("")), F.lit("\nAnswer: "), F.coalesce("response", F.lit("")), F.lit("\nGive a score and an explanation.")))


def parse_score(raw: Column, low: float = 1, high: float = 5) -> Column:
    """A score in ``score: x``, ``x/5``, ``[[x]]`` or JSON; null if none is there or it is off the scale."""
    tries = [F.get_json_object(raw, "$.score"), F.regexp_extract(raw, r"(?i)score['\"]?\s*[:=]\s*" + NUMBER, 1), F.regexp_extract(raw, r"\[\[" + NUMBER + r"\]\]", 1), F.regexp_extract(raw, NUMBER + r"\s*/\s*[0-9]+", 1)]
    value = F.coalesce(*(F.expr("try_cast(null as double)") if t is None else F.when(F.length(t) > 0, t).try_cast("double") for t in tries))
    return F.when((value >= low) & (value <= high), value)


def simulated_verdict(key: Column, quality: Column) -> Column:
    """A stand-in judge: a score near 1 + 4 * quality in one of four shapes; one answer in a hundred has none."""
    u, v = uniform(F.lit("judge"), key), uniform(F.lit("shape"), key)
    score = F.greatest(F.lit(1), F.least(F.lit(5), F.round(1 + 4 * quality + (u - 0.5)).cast("int"))).cast("string")
    shaped = F.when(v < 0.25, F.concat(F.lit("Score: "), score)).when(v < 0.5, F.concat(score, F.lit("/5 in all"))).when(v < 0.75, F.concat(F.lit("[["), score, F.lit("]]"))).otherwise(F.concat(F.lit('{"score": '), score, F.lit("}")))
    return F.when(u < 0.01, "a helpful answer").otherwise(shaped)


def unparsed(df: DataFrame, raw: str = "raw", score: str = "score") -> DataFrame:
    return df.where(F.col(raw).isNotNull() & F.col(score).isNull())


def prefer(first: Column, swapped: Column) -> Column:
    """One verdict from both orders (A, B or tie each): a choice that follows the position is a tie."""
    return F.when((first == "A") & (swapped == "B"), "A").when((first == "B") & (swapped == "A"), "B").otherwise("tie")


# Retrieval metrics.


def context_precision(df: DataFrame, query: str = "query_id", rank: str = "rank", relevant: str = "relevant", k: int = 10) -> DataFrame:
    """Mean precision at the ranks of relevant contexts; 0 where none is relevant."""
    w = Window.partitionBy(query).orderBy(rank).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    hit = F.col(relevant).cast("int")
    seen = df.where(F.col(rank) <= k).withColumn("hits", F.sum(hit).over(w))
    return seen.groupBy(query).agg(F.coalesce(F.avg(F.when(F.col(relevant), F.col("hits") / F.col(rank))), F.lit(0.0)).alias("precision"))


def context_recall(retrieved: DataFrame, relevant_total: DataFrame, query: str = "query_id") -> DataFrame:
    """Relevant contexts that were retrieved over all relevant ones (column ``total``)."""
    got = retrieved.groupBy(query).agg(F.count_if("relevant").alias("got"))
    return relevant_total.join(got, query, "left").select(query, F.try_divide(F.coalesce("got", F.lit(0)).cast("double"), "total").alias("recall"))


def claims(df: DataFrame, text: str = "response") -> DataFrame:
    """An answer's sentences, one a row."""
    return df.withColumn("claim", F.explode(F.filter(F.split(text, r"\. *"), lambda s: F.length(F.trim(s)) > 0)))


def faithfulness(df: DataFrame, supported: Column, id_col: str = "example_id") -> DataFrame:
    """Share of an answer's claims that ``supported`` (over ``claim`` and ``context``) holds; no claim: null."""
    judged = claims(df).withColumn("ok", supported.cast("int"))
    return df.select(id_col).join(judged.groupBy(id_col).agg(F.avg("ok").alias("faithfulness"), F.count("*").alias("claims")), id_col, "left")


def share_of_verdicts(df: DataFrame, verdicts: DataFrame, ok: Column, id_col: str = "example_id") -> DataFrame:
    """``faithfulness`` from stored verdicts, a row for each claim; an answer without claims has null."""
    found = verdicts.groupBy(id_col).agg(F.avg(ok.cast("int")).alias("faithfulness"), F.count("*").alias("claims"))
    return df.select(id_col).join(found, id_col, "left")


RARE = 4


def relevance_pairs(items: DataFrame, docs: DataFrame, doc_id: str = "doc_id") -> DataFrame:
    """Which documents hold a passage. Runs of ``RARE`` words of a passage are an equi-join key; among its runs the one that
    fewest documents hold is looked up, and the passage is compared with those documents only; texts stay out of the runs. A passage of fewer
    words, or one whose runs a document may cut at other characters than spaces, is compared with all documents."""
    def runs(text: Column) -> Column:
        run = lambda w: F.transform(F.sequence(F.lit(1), F.size(w) - RARE + 1), lambda i: F.xxhash64(*(F.get(w, i + (k - 1)) for k in range(RARE))))
        return F.array_distinct(F.get(F.transform(F.array(F.split(text, " ")), run), F.lit(0)))

    inner = F.regexp_replace("passage", "^[^ ]* | [^ ]*$", "")
    keyed = items.withColumn("_inner", inner).withColumn("_id", F.xxhash64("passage"))
    long = F.size(F.split("_inner", " ")) >= RARE
    wanted = keyed.where(long).select("_id", F.explode(runs(F.col("_inner"))).alias("run")).distinct()
    held = docs.where(F.size(F.split("doc_text", " ")) >= RARE).select(doc_id, F.explode(runs(F.col("doc_text"))).alias("run")).join(wanted.select("run").distinct().hint("merge"), "run", "left_semi")
    frequent = held.groupBy("run").agg(F.count("*").alias("n"))
    chosen = wanted.join(frequent, "run", "left").groupBy("_id").agg(F.min(F.struct(F.coalesce("n", F.lit(0)).alias("n"), "run")).alias("x")).select("_id", "x.run")
    met = held.join(keyed.where(long).join(chosen, "_id").drop("_id", "_inner").hint("merge"), "run").drop("run")
    by_run = docs.join(met, doc_id).where(F.contains("doc_text", "passage"))
    short = docs.join(items.withColumn("_inner", inner).where(~long).drop("_inner"), F.contains("doc_text", "passage"))
    return by_run.select(*docs.columns, *items.columns).unionByName(short.select(*docs.columns, *items.columns))


def chunks(df: DataFrame, text: str, size: int = 100, overlap: int = 20) -> DataFrame:
    """Overlapping runs of words of a document, one a row."""
    words = F.split(text, r"\s+")
    starts = F.sequence(F.lit(1), F.greatest(F.size(words), F.lit(1)), F.lit(size - overlap))
    return df.select("*", F.posexplode(F.transform(starts, lambda s: F.array_join(F.slice(words, s, size), " "))).alias("chunk_no", "chunk"))
