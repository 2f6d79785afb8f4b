"""Context calibration: haystacks, planted needles, the ladder of growing limits, finders, and what the trials say."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from catalogflow.functions.text import hash60, let, run_hash, shingles, tokens, word_hashes
from catalogflow.operators.metadata import VOTES
from catalogflow.session import staged


def ladder_grid(spark, start=10_000, step=500, ceiling=23_000, tests=4, patience=6) -> DataFrame:
    """All (test, level, attempt) that a ladder could need; a few hundred rows."""
    t = spark.range(1, tests + 1).select(F.col("id").cast("int").alias("test"))
    return t.crossJoin(spark.range(start, ceiling + 1, step).select(F.col("id").cast("int").alias("level"))).crossJoin(spark.range(1, patience + 1).select(F.col("id").cast("int").alias("attempt")))


def place_needle(grid: DataFrame, seed: str) -> DataFrame:
    """Adds pos (1 to level) and quartile, from a hash of the trial."""
    key = f"concat('{seed}', '/', cast(test as string), '/', cast(level as string), '/', cast(attempt as string))"
    out = grid.withColumn("h", hash60(key)).withColumn("pos", F.expr("cast(1 + h % level as int)"))
    return out.withColumn("quartile", F.expr("cast(least(4, 1 + (4 * (pos - 1)) div level) as int)"))


def simulated_finder(trials: DataFrame, seed: str, position: str = "end") -> DataFrame:
    """Adds raw, the answer of a SIMULATED reader: more errors above 19,000 characters and in the first half of the text.

    Rates per mille are invented but for the last: 160 errors below, 350 above; 60 more in quartiles 1 and 2, 60 fewer in 3 and 4; the format
    is kept in 780 answers where the demand for it opens the prompt, 740 in its middle, 850 at its end. Otherwise the answer is bare text.
    """
    rate = F.expr("(case when level > 19000 then 350 else 160 end) + (case when quartile <= 2 then 60 else -60 end)")
    draw = lambda kind, key: F.expr(f"cast(conv(substring(md5(concat('{seed}', '{kind}', {key})), 1, 15), 16, 10) as bigint) % 1000")
    answer = F.when(draw("e", "cast(h as string)") >= rate, F.col("needle")).otherwise(F.lit("NONE"))
    form = draw("j", "cast(h as string)") < JSON_RATES[position]
    return trials.withColumn("raw", F.when(form, F.to_json(F.struct(answer.alias("needle")))).otherwise(answer))


#: Answers per mille in the right format, by the place of the demand for it in the prompt; that for "end" is published, the others are invented.
JSON_RATES = {"start": 780, "middle": 740, "end": 850}


def exact_finder(trials: DataFrame) -> DataFrame:
    """Adds raw: the needle where the text holds it; the best that any reader can do."""
    return trials.withColumn("raw", F.to_json(F.struct(F.when(F.contains("text", F.col("needle")), F.col("needle")).otherwise(F.lit("NONE")).alias("needle"))))


def outlier_finder(trials: DataFrame, home: str) -> DataFrame:
    """Adds raw: the sentence of the text that looks least like the language ``home``."""
    return trials.withColumn("raw", F.to_json(F.struct(F.coalesce(outlier_sentence("text", home), F.lit("NONE")).alias("needle"))))


def endpoint_finder(trials: DataFrame, ask) -> DataFrame:
    """Adds raw by ``ask``, a function of an iterator of Arrow batches (prompt and all other columns) to batches with raw besides."""
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in trials.schema.fields)
    return trials.mapInArrow(ask, f"{fields}, raw string")


def run_ladder(answers: DataFrame, by: list[str] = ()) -> DataFrame:
    """The rows that a sequential ladder would have made, from all speculative ones, for each value of ``by``.

    At a level attempts go on to the first success; a level without success ends the test. Limits rise with each success, so
    a run of errors can only lie at one level.
    """
    at = Window.partitionBy(*by, "test", "level")
    up = Window.partitionBy(*by, "test").orderBy("level").rangeBetween(Window.unboundedPreceding, -1)
    first = F.min(F.when(F.col("correct"), F.col("attempt"))).over(at)
    kept = answers.withColumn("first", first).where("first is null or attempt <= first")
    return kept.withColumn("dead", F.coalesce(F.max(F.col("first").isNull().cast("int")).over(up), F.lit(0))).where("dead = 0").drop("first", "dead")


def run_ladder_sequential(grid_row, finder, start=10_000, step=500, ceiling=23_000, patience=6):
    """The same by a plain loop for one test: for paid endpoints and as a check. Yields (level, attempt, correct)."""
    level = start
    while level <= ceiling:
        for attempt in range(1, patience + 1):
            ok = finder(grid_row, level, attempt)
            yield level, attempt, ok
            if ok:
                break
        else:
            return
        level += step


def errors_by_quartile(trials: DataFrame, by: list[str] = ()) -> DataFrame:
    return trials.groupBy(*by, "quartile").agg(F.count("*").alias("n"), F.count_if(~F.col("correct")).alias("errors")).withColumn("share", F.round(F.col("errors") / F.col("n"), 6))


def errors_by_limit(trials: DataFrame, by: list[str] = ()) -> DataFrame:
    """Per limit, per band and in all (nulls)."""
    band = F.expr("case when level <= 19000 then 'low' else 'high' end")
    t = trials.select(*by, band.alias("band"), "level", "correct")
    sets = [[*by, "band", "level"], [*by, "band"], [*by]]
    return t.groupingSets(sets, *by, "band", "level").agg(F.count("*").alias("n"), F.count_if(~F.col("correct")).alias("errors"))


def choose_budget(trials: DataFrame, max_error: float, by: list[str] = ()) -> DataFrame:
    """The largest limit up to which the cumulative share of errors stays within ``max_error``; null where the first is above."""
    per = trials.groupBy(*by, "level").agg(F.count("*").alias("n"), F.count_if(~F.col("correct")).alias("errors"))
    w = Window.partitionBy(*by).orderBy("level") if by else Window.orderBy("level")
    run = per.withColumn("share", F.sum("errors").over(w) / F.sum("n").over(w)).withColumn("bad", F.max((F.col("share") > max_error).cast("int")).over(w))
    return run.groupBy(*by).agg(F.max(F.when(F.col("bad") == 0, F.col("level"))).alias("budget"))


def haystacks(docs: DataFrame, tests: int, seed: str, lang: str, ceiling: int = 23_000) -> DataFrame:
    """(test, text): documents of one language per test, in hashed order, until their length reaches ``ceiling``.

    Only documents whose hash is below a threshold are put in order: so small that they hold some 16 times the characters needed, and
    widened to all if a test should fall short. So no sort sees the corpus.
    """
    own = docs.where((F.col("lang") == lang) & F.col("text").isNotNull())
    total = own.agg(F.sum(F.length("text"))).first()[0] or 0
    share = min(1.0, 16 * ceiling / max(1, total))
    while True:
        d = own.select("doc_id", "text", F.explode(F.array(*[F.lit(t) for t in range(1, tests + 1)])).alias("test"))
        d = d.withColumn("k", hash60(f"concat('{seed}/', cast(test as string), '/', cast(doc_id as string))")).where(F.col("k") <= int(share * ((1 << 60) - 1)))
        run = Window.partitionBy("test").orderBy("k", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
        top = d.withColumn("before", F.coalesce(F.sum(F.length("text") + 1).over(run), F.lit(0))).where(F.col("before") < ceiling)
        out = top.groupBy("test").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("before", "text"))), lambda s: s["text"]), " ").alias("text"))
        out = staged(out, "haystacks")
        if share >= 1 or out.where(F.length("text") >= ceiling).count() == tests:
            return out
        share = 1.0


def plant(trials: DataFrame, hay: DataFrame, needle: str | Column) -> DataFrame:
    """Adds needle, and text: the haystack cut to the limit, the needle put in as a sentence behind the one that holds the place.

    The haystacks are broadcast: one text of the ladder's ceiling for each test.
    """
    n = F.lit(needle) if isinstance(needle, str) else needle
    cut = trials.join(F.broadcast(hay), "test").withColumn("hay", F.expr("substring(text, 1, level)")).withColumn("needle", n)
    stop = F.expr("case when locate('.', hay, pos) = 0 then length(hay) else locate('.', hay, pos) end")
    return cut.withColumn("stop", stop).withColumn("text", F.concat(F.expr("substring(hay, 1, stop)"), F.lit(" "), F.col("needle"), F.lit("."), F.expr("substring(hay, stop + 1)"))).drop("hay", "stop")


ASK = "One sentence below does not belong to the rest. Which one?"
FORM = 'Reply only with {"needle": "..."}; write NONE there if all sentences belong.'


def needle_prompt(trials: DataFrame, position: str = "end") -> DataFrame:
    """Adds prompt; where the demand for JSON stands is an option: start, middle or end."""
    ask, form = F.lit(ASK), F.lit(FORM)
    parts = {"start": [form, ask, F.col("text")], "middle": [ask, form, F.col("text")], "end": [ask, F.col("text"), form]}[position]
    return trials.withColumn("prompt", F.concat_ws("\n", *parts))


def outlier_sentence(text: str | Column, home: str) -> Column:
    """The sentence with most frequent words of other languages over those of ``home`` (ties: the first)."""
    t = F.col(text) if isinstance(text, str) else text
    own = VOTES[home].split()
    other = [w for x, ws in VOTES.items() if x != home for w in ws.split() if w not in own]
    sentences = F.filter(F.split(t, "[.]"), lambda s: F.trim(s) != "")
    count = lambda s, ws: F.size(F.filter(tokens(s), lambda w: w.isin(*ws)))
    scored = let(sentences, lambda all_: F.transform(all_, lambda s, i: F.struct((count(s, other) - count(s, own)).alias("v"), (-i).alias("i"), F.trim(s).alias("s"))))
    return F.array_max(scored)["s"]


def grade_needle(answers: DataFrame) -> DataFrame:
    """Adds json_ok and correct to rows (raw, needle): the answer is a JSON object, and holds the needle (in its key, or bare)."""
    found = F.coalesce(F.get_json_object("raw", "$.needle"), F.col("raw"))
    return answers.withColumn("json_ok", F.coalesce(F.get_json_object("raw", "$").startswith("{"), F.lit(False))).withColumn("correct", F.coalesce(F.contains(found, F.col("needle")), F.lit(False)))


def find_passages(docs: DataFrame, bench: DataFrame, k: int = 5) -> DataFrame:
    """(doc_id, item_id, pos, quartile) of passages that stand in documents letter for letter, wherever they begin or end.

    The first and last word of a passage may be parts of longer words in a document, so candidates share the k words after the first.
    Hashes of word runs, without texts, meet the passages' seeds; only documents with a hit are read again for the substring search.
    Passages without k inner words are compared directly with every document, in blocks of documents and of passages.
    """
    p = bench.select("item_id", F.col("text").alias("passage"), tokens().alias("w")).where("passage <> ''")
    p = p.select("item_id", "passage", F.when(F.size("w") >= k + 2, run_hash(word_hashes(F.col("w")), F.lit(1), k)).alias("seed"))
    runs = docs.select("doc_id", F.explode(shingles(tokens(), k)).alias("seed"))
    near = runs.join(p.where("seed is not null").select("item_id", "seed"), "seed").select("doc_id", "item_id").distinct()
    near = near.join(p.select("item_id", "passage"), "item_id").join(docs.select("doc_id", "text"), "doc_id")
    short = docs.select("doc_id", "text").crossJoin(p.where("seed is null").select("item_id", "passage"))
    both = near.select("doc_id", "text", "item_id", "passage").union(short.select("doc_id", "text", "item_id", "passage"))
    pos = F.instr("text", F.col("passage"))
    return both.withColumn("pos", pos).where("pos > 0").select("doc_id", "item_id", "pos", F.expr("cast(least(4, 1 + (4 * (pos - 1)) div length(text)) as int)").alias("quartile"))
