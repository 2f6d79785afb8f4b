"""Labelling: taxonomies, expert scoring, selection of labels, sampling of example sets, prompts and their packing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from catalogflow.functions.text import CATALOG, TOKEN_SPLIT, hash60, tokens
from catalogflow.operators.extract import text_elements
from catalogflow.operators.metadata import VOTES, language_votes
from catalogflow.session import staged

#: domain -> labels; origin has two levels, written "inner, leaf".
TX1 = {"origin": ["germanic, en", "germanic, de", "romance, fr", "romance, es"], "condition": ["clean", "noisy"], "conduct": ["civil", "abusive"]}
INNER = {"germanic": "origin", "romance": "origin"}
DEFINITIONS = {
    "germanic, en": "written in English", "germanic, de": "written in German", "romance, fr": "written in French", "romance, es": "written in Spanish",
    "clean": "running prose with usual punctuation", "noisy": "littered with symbols", "civil": "free of insults", "abusive": "holds insults",
}
ABUSE = "trash idiot clown scum worthless moron pathetic loser stupid disgusting"
TX2 = {"ECONOMY": "value", "PROMO": "value", "STANDARD": "core", "MEDIUM": "core", "SMALL": "size", "LARGE": "size"}
ORIGIN_OF = {"en": "germanic, en", "de": "germanic, de", "fr": "romance, fr", "es": "romance, es"}
BUDGET = 15_000


def expert_scores(docs: DataFrame, keep: list[str] = (), reasons: bool = False) -> DataFrame:
    """(doc_id, domain, label, score 1..5): one expert for each domain scores all of its labels; with its reason if asked. One scan, no shuffle."""
    own = ABUSE.split()
    d = language_votes(docs, more=tuple(own))
    d = d.withColumn("insults", F.size(F.filter("tok_", lambda t: t.isin(*own))))
    d = d.withColumn("sym_", F.expr("length(regexp_replace(text, '[A-Za-zÀ-ÿ \\n.,]+', '')) / cast(greatest(length(text), 1) as double)"))
    symbols = F.col("sym_")
    d = d.withColumn("noisy", F.when(symbols <= 0.005, 1).when(symbols <= 0.01, 2).when(symbols <= 0.02, 3).when(symbols <= 0.05, 4).otherwise(5))
    d = d.withColumn("abusive", F.when(F.col("insults") == 0, 1).when(F.col("insults") == 1, 4).otherwise(5))
    total = sum((F.col(f"v_{x}") for x in VOTES), F.lit(0))
    d = d.withColumn("all_", total)

    def row(domain, label, score, why):
        return F.struct(F.lit(domain).alias("domain"), F.lit(label).alias("label"), score.cast("int").alias("score"), *([why.alias("reason")] if reasons else []))

    text = lambda c: c.cast("string")
    shared = F.concat(text(F.floor(symbols * 1000)), F.lit(" symbols in a thousand"))
    insults = F.concat(text(F.col("insults")), F.lit(" insults"))
    origin = [
        row("origin", ORIGIN_OF[x], F.when(F.col("all_") == 0, 1).otherwise(1 + F.least(F.lit(4), F.expr(f"(5 * v_{x}) div all_"))), F.concat(text(F.col(f"v_{x}")), F.lit(" of "), text(F.col("all_")), F.lit(" frequent words")))
        for x in VOTES
    ]
    rest = [row("condition", "noisy", F.col("noisy"), shared), row("condition", "clean", 6 - F.col("noisy"), shared), row("conduct", "abusive", F.col("abusive"), insults), row("conduct", "civil", 6 - F.col("abusive"), insults)]
    return d.select("doc_id", *keep, F.inline(F.array(*origin, *rest)))


def select_labels(scores: DataFrame, item: str = "doc_id", threshold: int = 4, per: str = "item") -> DataFrame:
    """Labels of at least ``threshold``; where none reaches it, all that share the highest score. per: 'item' or 'domain'."""
    w = Window.partitionBy(item) if per == "item" else Window.partitionBy(item, "domain")
    return scores.withColumn("top_", F.max("score").over(w)).where(f"score >= {threshold} or (top_ < {threshold} and score = top_)").drop("top_")


def gold_labels(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, domain, label) of labelled documents."""
    j = docs.select("doc_id", "lang").join(labels, "doc_id")
    origin = F.create_map(*[F.lit(x) for kv in ORIGIN_OF.items() for x in kv])
    row = lambda dom, c: F.struct(F.lit(dom).alias("domain"), c.alias("label"))
    return j.select("doc_id", F.inline(F.array(row("origin", F.try_element_at(origin, F.col("lang"))), row("condition", F.expr("case when quality = 0 then 'noisy' else 'clean' end")), row("conduct", F.expr("case when toxic = 1 then 'abusive' else 'civil' end")))))


def order_scores(lineitem: DataFrame, part: DataFrame) -> DataFrame:
    """(o, domain, label, score, gold) per order and type of part: score from the mean quantity, gold from the share in revenue."""
    # spread by order once: of an order's lines hardly two have one type, so nothing is lost by not combining before
    j = lineitem.select("l_orderkey", "l_partkey", "l_quantity", "l_extendedprice").join(part.select("p_partkey", "p_type"), F.col("l_partkey") == F.col("p_partkey")).repartition("l_orderkey")
    per = j.groupBy(F.col("l_orderkey").alias("o"), F.col("p_type").alias("label")).agg(F.avg("l_quantity").alias("q"), F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).alias("rev"))
    domain = F.create_map(*[F.lit(x) for kv in TX2.items() for x in kv])
    out = per.withColumn("all_", F.sum("rev").over(Window.partitionBy("o"))).withColumn("score", F.least(F.lit(5), F.ceil(F.round(F.col("q") / 10, 9))).cast("int"))
    return out.select("o", F.try_element_at(domain, F.col("label")).alias("domain"), "label", "score", (F.col("rev") * 4 >= F.col("all_")).alias("gold"))


def panel_votes(docs: DataFrame) -> DataFrame:
    """(doc_id, e0, e1, e2, s0, s1, s2, label, agreed): three generic experts, each with a third of the frequent words.

    Each answers with a language (none without a word) and scores the others' answers from 1 to 5 by the share of its own words that speak
    for them; s0 to s2 sum what an answer got from its two peers. Consensus is what two of them say; else the answer with the best
    score (ties: alphabetical).
    """
    order = sorted(VOTES)
    every = sorted({w for ws in VOTES.values() for w in ws.split()})
    d = docs.select("doc_id", F.filter(F.split(F.lower("text"), TOKEN_SPLIT), lambda t: t.isin(*every)).alias("tok"))
    for e in range(3):
        for x in order:
            own = VOTES[x].split()[e::3]
            d = d.withColumn(f"p{e}_{x}", F.size(F.filter("tok", lambda t: t.isin(*own))))
    for e in range(3):
        most = F.greatest(*[F.col(f"p{e}_{x}") for x in order])
        out = F.when(most == 0, F.lit(None).cast("string"))
        for x in order:
            out = out.when(F.col(f"p{e}_{x}") == most, F.lit(x))
        d = d.withColumn(f"e{e}", out).withColumn(f"t{e}", sum((F.col(f"p{e}_{x}") for x in order), F.lit(0)))

    def peer(judge: int, said: int) -> Column:
        own = F.lit(0)
        for x in order:
            own = F.when(F.col(f"e{said}") == x, F.col(f"p{judge}_{x}")).otherwise(own)
        return F.when(F.col(f"t{judge}") == 0, 1).otherwise(1 + F.least(F.lit(4), F.floor(5 * own / F.col(f"t{judge}"))))

    for e in range(3):
        d = d.withColumn(f"s{e}", F.when(F.col(f"e{e}").isNull(), 0).otherwise(sum((peer(f, e) for f in range(3) if f != e), F.lit(0))).cast("int"))
    pair = F.expr("case when e0 = e1 or e0 = e2 then e0 when e1 = e2 then e1 end")
    answers = F.filter(F.array(*[F.struct((-F.col(f"s{e}")).alias("s"), F.col(f"e{e}").alias("label")) for e in range(3)]), lambda a: a["label"].isNotNull())
    guess = F.get(F.array_sort(answers), F.lit(0))["label"]
    return d.select("doc_id", "e0", "e1", "e2", "s0", "s1", "s2", F.coalesce(pair, guess).alias("label"), pair.isNotNull().alias("agreed"))


def round_robin(items: DataFrame, seed: str, catalogs: int = 4) -> DataFrame:
    """Adds pos: one random item of each catalogue in turn. Sorted within a catalogue, never globally."""
    w = Window.partitionBy("catalog_id").orderBy(F.md5(F.concat(F.lit(seed), F.col("doc_id").cast("string"))), "doc_id")
    return items.withColumn("pos", ((F.row_number().over(w) - 1) * catalogs + F.col("catalog_id") + 1).cast("int"))


def covering_set(ordered: DataFrame, gold: DataFrame) -> DataFrame:
    """The shortest prefix in order of pos that holds every label."""
    first = gold.join(ordered.select("doc_id", "pos"), "doc_id").groupBy("domain", "label").agg(F.min("pos").alias("p"))
    return ordered.crossJoin(F.broadcast(first.agg(F.max("p").alias("cut")))).where("pos <= cut").drop("cut")


def covering_sets(items: DataFrame, gold: DataFrame, seed: str) -> DataFrame:
    """(doc_id, catalog_id, pos, dataset): set A, then a disjoint set B from what is left, renumbered."""
    a = covering_set(round_robin(items, seed), gold).withColumn("dataset", F.lit("A"))
    left = items.join(a.select("doc_id"), "doc_id", "left_anti")
    b = covering_set(round_robin(left, seed), gold).withColumn("dataset", F.lit("B"))
    return a.unionByName(b).select("doc_id", "catalog_id", "pos", "dataset")


def swap_plan(sets: DataFrame) -> DataFrame:
    """(fold, role, doc_id): train on A and test on B, then the other way round."""
    folds = F.explode(F.array(F.lit(1), F.lit(2))).alias("fold")
    return sets.select("doc_id", "dataset", folds).select("fold", F.expr("case when (dataset = 'A') = (fold = 1) then 'train' else 'test' end").alias("role"), "doc_id")


def taxonomy_prompt(spark, tax: dict[str, list[str]], version: int) -> DataFrame:
    """(version, prompt): the labels with their definitions, in order."""
    text = "\n".join(f"[{d}] " + " / ".join(f"{x}: {DEFINITIONS.get(x, x)}" for x in labels) for d, labels in tax.items())
    return spark.createDataFrame([(version, f"Taxonomy, version {version}.\n{text}")], "version int, prompt string")


def taxonomy_diff(old: DataFrame, new: DataFrame) -> DataFrame:
    """(change, domain, label) between two versions of (domain, label)."""
    return old.exceptAll(new).select(F.lit("removed").alias("change"), "domain", "label").union(new.exceptAll(old).select(F.lit("added").alias("change"), "domain", "label"))


def item_json() -> Column:
    """A JSON object of an item's name and description."""
    return F.to_json(F.struct(F.coalesce("name", F.lit("")).alias("name"), F.coalesce("description", F.lit("")).alias("description")))


def fewshot_prompts(docs: DataFrame, gold: DataFrame) -> DataFrame:
    """(doc_id, prompt): a worked example, which no answer is wanted for: the item and its answer as JSON, with a reason per label.

    A label's reason is a fixed expression, filled with what the domain's expert finds in the item.
    """
    defined = F.create_map(*[F.lit(x) for k, v in DEFINITIONS.items() for x in (k, v)])
    found = expert_scores(docs, reasons=True).select("doc_id", "domain", "label", "reason")
    why = F.concat(F.lit("It is "), F.col("label"), F.lit(" because the text is "), F.try_element_at(defined, F.col("label")), F.lit(": "), F.coalesce("reason", F.lit("no evidence")), F.lit("."))
    per = gold.join(found, ["doc_id", "domain", "label"], "left").groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("label", why.alias("why")))).alias("x"))
    answer = F.to_json(F.struct(F.transform("x", lambda e: e["label"]).alias("labels"), F.array_join(F.transform("x", lambda e: e["why"]), " ").alias("reason")))
    j = text_elements(docs.select("doc_id", "text")).join(per, "doc_id")
    return j.select("doc_id", F.concat_ws("\n", F.lit("== SHOT =="), item_json(), answer, F.lit("(for context only)")).alias("prompt"))


def item_prompts(docs: DataFrame) -> DataFrame:
    """(doc_id, prompt): an item to be labelled, as JSON, and what is wanted."""
    ask = F.lit("Score every label of your domain from 1 to 5; give those of 4 and more, or the highest. Answer with one JSON object, a list of labels for each domain.")
    return text_elements(docs.select("doc_id", "text")).select("doc_id", F.concat_ws("\n", F.lit("== ITEM =="), item_json(), ask).alias("prompt"))


def run_classification(docs: DataFrame, gold: DataFrame, sets: DataFrame, labeller, shot_chars: int = 1_000, budget: int = BUDGET, max_prompts: int = 10) -> DataFrame:
    """A whole labelling run: (fold, conv, turn, kind, prompt_no, doc_id, chars, prompts, raw).

    Both roles of the sets: shots of one, items of the other. A conversation opens with the taxonomy, gives the packed shots and
    then asks for items, of which as many conversations are made, as even as can be, as keep each within ``max_prompts`` (one item
    each, where the shots alone fill it). Texts are condensed first, to ``shot_chars`` and to the ``budget`` of a prompt. ``labeller``
    takes documents (doc_id, text) and gives (doc_id, raw) answers.
    """
    sets = staged(sets, "run-sets")
    plan = swap_plan(sets).join(sets.select("doc_id", "pos"), "doc_id")
    own = staged(docs.join(sets.select("doc_id"), "doc_id", "left_semi").select("doc_id", "text"), "run-items")
    gold = gold.join(sets.select("doc_id"), "doc_id", "left_semi")
    shot = fewshot_prompts(condense(own, shot_chars), gold).select("doc_id", F.length("prompt").cast("bigint").alias("chars"))
    train = plan.where("role = 'train'").join(shot, "doc_id").select(F.col("fold").alias("grp"), F.col("pos").cast("bigint").alias("ord"), "chars")
    packed = staged(pack_prompts(train, budget).groupBy(F.col("grp").alias("fold"), "prompt_no").agg(F.sum("chars").alias("chars")), "run-shots")
    full = condense(own, budget).select("doc_id", "text")
    ask = item_prompts(full).select("doc_id", F.length("prompt").cast("bigint").alias("chars"))
    test = plan.where("role = 'test'").join(ask, "doc_id")
    number = Window.partitionBy("fold")
    # a run's sets are a few dozen items: these tables of counts are smaller still
    size = packed.groupBy("fold").agg(F.max("prompt_no").alias("shots"))
    item = test.withColumn("i", F.row_number().over(number.orderBy("pos", "doc_id"))).withColumn("n", F.count("*").over(number)).join(size, "fold")
    item = item.withColumn("convs", F.expr(f"cast(ceil(n / greatest(1, {max_prompts - 1} - shots)) as bigint)")).withColumn("conv", F.expr("cast((i - 1) * convs div n as int)"))
    item = staged(item, "run-turns").withColumn("turn", (F.row_number().over(Window.partitionBy("fold", "conv").orderBy("i")) + F.col("shots") + 1).cast("int"))
    talks = item.select("fold", "conv").distinct()
    head = taxonomy_prompt(docs.sparkSession, TX1, 1).select(F.length("prompt").cast("bigint").alias("chars"))
    none = F.lit(None).cast("bigint").alias("doc_id")
    first = talks.crossJoin(head).select("fold", "conv", F.lit(1).alias("turn"), F.lit("taxonomy").alias("kind"), none, "chars")
    shots = talks.join(packed, "fold").select("fold", "conv", (F.col("prompt_no") + 1).cast("int").alias("turn"), F.lit("shots").alias("kind"), none, "chars")
    items = item.select("fold", "conv", "turn", F.lit("item").alias("kind"), "doc_id", "chars")
    out = first.union(shots).union(items).withColumn("prompts", F.count("*").over(Window.partitionBy("fold", "conv")))
    return out.join(labeller(full), "doc_id", "left")


def pack_prompts(shots: DataFrame, budget: int = BUDGET) -> DataFrame:
    """(grp, prompt_no, ord, chars, oversize): next fit within each group in order; a shot above the budget is a prompt of its own.

    Folds over one group's (order, length) pairs, which is what a conversation's worth of shots comes to; texts aren't collected.
    """
    rows = shots.groupBy("grp").agg(F.array_sort(F.collect_list(F.struct("ord", "chars"))).alias("s"))
    start = F.struct(F.lit(0).alias("no"), F.lit(budget + 1).cast("bigint").alias("used"), F.array().cast("array<struct<ord:bigint,chars:bigint,prompt_no:int>>").alias("out"))

    def step(acc, x):
        fits = acc["used"] + x["chars"] <= budget
        no = F.when(fits, acc["no"]).otherwise(acc["no"] + 1)
        used = F.when(fits, acc["used"] + x["chars"]).otherwise(x["chars"])
        row = F.struct(x["ord"].cast("bigint").alias("ord"), x["chars"].cast("bigint").alias("chars"), no.alias("prompt_no"))
        return F.struct(no.alias("no"), used.cast("bigint").alias("used"), F.concat(acc["out"], F.array(row)).alias("out"))

    out = rows.select("grp", F.inline(F.aggregate("s", start, step, lambda a: a["out"])))
    return out.withColumn("oversize", F.col("chars") > budget)


def plan_conversations(n_shot_prompts: int, n_items: int, max_prompts: int = 10) -> list[list[int]]:
    """Item numbers (from 1) per conversation: taxonomy, shot prompts and items stay within ``max_prompts``; halves as even as can be."""
    room = max_prompts - 1 - n_shot_prompts
    if room < 1:
        raise ValueError("no room for items")
    convs = max(1, -(-n_items // room))
    return [[i for i in range(1, n_items + 1) if (i - 1) * convs // n_items == c] for c in range(convs)]


def condense(docs: DataFrame, max_chars: int) -> DataFrame:
    """(doc_id, text, cut) for every row: the sentences with most words of more than four letters that fit in the budget, in their own order.

    Sentences are ranked (ties: earlier first); those that don't fit any more are passed over. Where none fits, the best one is cut at a word border (inside the word, if it is longer than the budget) and ``cut`` is true.
    Null texts stay null; a longer text of nothing but full stops and blanks becomes ''. No shuffle.
    """
    s = F.transform(F.split("text", "[.]"), lambda s, i: F.struct((-F.size(F.filter(tokens(s), lambda t: F.length(t) > 4))).alias("w"), i.alias("i"), s.alias("s")))
    ranked = F.array_sort(F.filter(s, lambda x: F.trim(x["s"]) != ""))
    start = F.struct(F.lit(0).alias("used"), F.array().cast("array<struct<i:int,s:string>>").alias("out"))

    def step(acc, x):
        room = acc["used"] + F.length(x["s"]) + 1
        more = F.concat(acc["out"], F.array(F.struct(x["i"].alias("i"), x["s"].alias("s"))))
        return F.when(room <= max_chars, F.struct(room.alias("used"), more.alias("out"))).otherwise(acc)

    kept = F.aggregate("ranked", start, step, lambda a: F.transform(F.array_sort(a["out"]), lambda x: x["s"]))
    best = F.trim(F.get("ranked", F.lit(0))["s"])
    word = F.regexp_extract(F.substring(best, 1, max_chars + 1), r"(?s)^(.*)\s", 1)
    short = F.when(F.length(best) <= max_chars, best).when(word != "", word).otherwise(F.substring(best, 1, max_chars))
    long = docs.where(F.length("text") > max_chars).select("doc_id", ranked.alias("ranked")).select("doc_id", "ranked", kept.alias("kept"))
    none = F.size("kept") == 0
    text = F.when(F.size("ranked") == 0, F.lit("")).when(none, short).otherwise(F.array_join("kept", "."))
    cut = long.select("doc_id", text.alias("text"), (none & (F.size("ranked") > 0)).alias("cut"))
    return cut.union(docs.where(F.coalesce(F.length("text"), F.lit(0)) <= max_chars).select("doc_id", "text", F.lit(False)))


def context_leakage(conv: DataFrame, n: int = 3) -> DataFrame:
    """(conv_id, turn, own, prior, leaked): word runs that an answer shares with its question, and with earlier ones of the talk only."""
    from catalogflow.functions.text import shingles

    t = conv.select("conv_id", "turn", "role", shingles(tokens(), n).alias("sh"))
    users = t.where("role = 'user'").select("conv_id", F.col("turn").alias("ut"), F.col("sh").alias("us"))
    pairs = t.where("role = 'assistant'").join(users, "conv_id").where("ut < turn")
    both = F.size(F.array_intersect("sh", "us"))
    per = pairs.select("conv_id", "turn", "ut", both.alias("c"))
    last = F.max("ut").over(Window.partitionBy("conv_id", "turn"))
    g = per.withColumn("own_t", last).groupBy("conv_id", "turn").agg(F.sum(F.expr("case when ut = own_t then c else 0 end")).alias("own"), F.sum(F.expr("case when ut < own_t then c else 0 end")).alias("prior"))
    return g.withColumn("leaked", F.col("prior") > F.col("own"))


def revise_gold(gold: DataFrame, proposals: DataFrame) -> DataFrame:
    """(doc_id, domain, label, state): kept, added (accepted proposals) or removed (refused labels); proposals: + action, accepted."""
    p = proposals.where("accepted").select("doc_id", "domain", "label", "action")
    j = gold.withColumn("had", F.lit(True)).join(p, ["doc_id", "domain", "label"], "full")
    return j.select("doc_id", "domain", "label", F.expr("case when had and action = 'remove' then 'removed' when had then 'kept' when action = 'add' then 'added' end").alias("state")).where("state is not null")


def retrieve_shots(docs: DataFrame, library: DataFrame, k: int = 1) -> DataFrame:
    """(doc_id, shot_id, score, rank): nearest shots by token Jaccard. The library is a covering set, a few dozen rows, and broadcast."""
    a = docs.select("doc_id", F.array_distinct(tokens()).alias("w"))
    b = library.select(F.col("doc_id").alias("shot_id"), F.array_distinct(tokens()).alias("sw"))
    both = F.size(F.array_intersect("w", "sw"))
    s = a.crossJoin(F.broadcast(b)).where("doc_id <> shot_id").select("doc_id", "shot_id", F.round(both / F.greatest(F.lit(1), F.size("w") + F.size("sw") - both), 6).alias("score"))
    w = Window.partitionBy("doc_id").orderBy(F.desc("score"), "shot_id")
    return s.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def train_classifier(docs: DataFrame, label: str, algo: str, features: int = 1 << 14):
    """A fitted pipeline of Spark ML: hashed words to ``label``; algo 'nb' or 'lr'."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression, NaiveBayes
    from pyspark.ml.feature import HashingTF, StringIndexer

    last = NaiveBayes(labelCol="y", featuresCol="x") if algo == "nb" else LogisticRegression(labelCol="y", featuresCol="x", maxIter=10, regParam=0.01)
    return Pipeline(stages=[StringIndexer(inputCol=label, outputCol="y", handleInvalid="skip"), HashingTF(inputCol="tok", outputCol="x", numFeatures=features), last]).fit(docs)


def dataset_items(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, catalog_id) of labelled tool items."""
    return docs.select("doc_id", F.expr(CATALOG).alias("catalog_id")).where("catalog_id < 4").join(labels.select("doc_id"), "doc_id", "left_semi")


def learn_lexicon(docs: DataFrame, gold: DataFrame, domain: str, top: int = 20) -> DataFrame:
    """(label, token, weight): the ``top`` tokens per label by log odds of document frequency in the training items."""
    g = gold.where(F.col("domain") == domain).select("doc_id", "label")
    n = g.groupBy("label").agg(F.count("*").alias("n"))
    t = docs.select("doc_id", F.explode(F.array_distinct(tokens())).alias("token")).join(g, "doc_id").groupBy("label", "token").agg(F.count("*").alias("df"))
    every = t.groupBy("token").agg(F.sum("df").alias("all_df"))
    total = n.agg(F.sum("n").alias("all_n"))
    odds = t.join(every, "token").join(F.broadcast(n), "label").crossJoin(F.broadcast(total))
    odds = odds.withColumn("weight", F.round(F.ln(F.expr("(df + 0.5) / (n + 1)")) - F.ln(F.expr("(all_df - df + 0.5) / (all_n - n + 1)")), 6)).where("df >= 2")
    w = Window.partitionBy("label").orderBy(F.desc("weight"), "token")
    return odds.withColumn("r", F.row_number().over(w)).where(F.col("r") <= top).select("label", "token", "weight")


def lexicon_labels(docs: DataFrame, lexicon: DataFrame, prior: DataFrame) -> DataFrame:
    """(doc_id, label): the label with most weight among a document's tokens; without any token, the prior's label (one row)."""
    t = docs.select("doc_id", F.explode(F.array_distinct(tokens())).alias("token")).join(F.broadcast(lexicon), "token")
    s = t.groupBy("doc_id", "label").agg(F.round(F.sum("weight"), 6).alias("w"))
    best = s.groupBy("doc_id").agg(F.max(F.struct("w", "label"))["label"].alias("found"))
    return docs.select("doc_id").crossJoin(F.broadcast(prior)).join(best, "doc_id", "left").select("doc_id", F.coalesce("found", "prior").alias("label"))


def random_labels(items: DataFrame, gold: DataFrame, seed: str) -> DataFrame:
    """(doc_id, domain, label): for each item and domain a label drawn with the gold labels' frequencies, by a hash. One row per label is broadcast."""
    n = gold.groupBy("domain", "label").agg(F.count("*").alias("n"))
    w = Window.partitionBy("domain").orderBy("label")
    prior = n.withColumn("upto", F.sum("n").over(w)).withColumn("all_", F.sum("n").over(Window.partitionBy("domain")))
    drawn = items.select("doc_id").crossJoin(F.broadcast(prior)).withColumn("u", hash60(f"concat('{seed}/', domain, '/', cast(doc_id as string))") % F.col("all_"))
    return drawn.where("u < upto and u >= upto - n").select("doc_id", "domain", "label")
