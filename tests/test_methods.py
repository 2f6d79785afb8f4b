"""Worked examples and invariants of the method's own operators."""

import itertools
from datetime import datetime

import pytest
from hypothesis import given
from hypothesis import settings as hyp
from hypothesis import strategies as st
from pyspark.sql import functions as F

from catalogflow.operators import answers as A
from catalogflow.operators import classify as C
from catalogflow.operators import dedup as D
from catalogflow.operators import extract as X
from catalogflow.operators import load as L
from catalogflow.operators import metadata as MD
from catalogflow.operators import metrics as M
from catalogflow.operators import probe as P
from catalogflow.operators.graph import connected_groups
from catalogflow.session import fresh_path, table
from catalogflow.streaming import traffic as S


def rows(df):
    return [tuple(r) for r in df.collect()]


# duplicates


@pytest.fixture(scope="module")
def small_items(spark):
    data = [
        (1, 0, "alpha", "p", "ECONOMY"), (2, 1, "alpha", "p", "ECONOMY"), (3, 0, "beta", "q", "SMALL"), (4, 1, "gamma", "q", "LARGE"),
        (5, 1, "delta", "r", "STANDARD"), (6, 2, "beta two", "q", "SMALL"), (7, 3, "omega", "z", "PROMO"),
    ]
    return spark.createDataFrame(data, "id bigint, catalog_id int, name string, producer string, type string")


def test_names_first(small_items):
    assert rows(D.match_by_name(small_items).select("a", "b")) == [(1, 2)]


def test_links_join_the_same_items_as_pairs(spark):
    items = spark.createDataFrame([(i, i % 3, "x", "p") for i in range(1, 41)] + [(50, 1, "y", "p"), (53, 1, "y", "p"), (60, 0, None, "p"), (61, 1, None, "p")], "id bigint, catalog_id int, name string, producer string")
    links = D.name_links(items)
    assert links.count() == 39 and sorted(rows(connected_groups(links))) == sorted(rows(connected_groups(D.match_by_name(items))))


def test_cascade_by_links_removes_the_same_items(spark):
    data = [(i, i % 3, i % 2, "x", "en", "") for i in range(1, 10)] + [(20, 0, 1, "y", "de", ""), (21, 2, 2, "z", "de", ""), (22, 1, 1, "", "de", ""), (23, 2, 1, "", "de", "")]
    items = spark.createDataFrame(data, "doc_id bigint, catalog_id int, edition int, name string, type string, text string")
    judged = spark.createDataFrame([(20, 21, "same", 0.9, "r"), (1, 20, "same", 0.8, "r")], "a bigint, b bigint, verdict string, score double, reason string")
    found = [D.text_cascade(items, D.associations(spark, D.TEXT_ASSOCIATIONS), judged=judged, links=x) for x in (False, True)]
    assert found[1].where("stage = 'name'").count() == 8 < found[0].where("stage = 'name'").count()
    gone = [sorted(rows(D.removed_items(items, f))) for f in found]
    assert gone[0] == gone[1] and len(gone[0]) == 9


def test_baselines_count_what_their_sql_lists(spark, tmp_path, monkeypatch):
    """Copies in several languages and catalogues, names in common, wholes, texts of one size that hold each other, repeated rows, nulls; no pairs by name are made."""
    import random

    import duckdb

    from catalogflow.queries import ORACLES, QUERIES

    rng = random.Random(5)
    say = lambda n: " ".join("".join(rng.choices("abcdefgh", k=6)) for _ in range(n))
    base = [f"{say(2)}. {say(30)}" for _ in range(12)]
    texts = base * 5 + [f"{base[i]} {base[i + 1]}" for i in range(11)] * 2 + [b + " " + say(4) for b in base] * 2 + [f"{base[0].split('.')[0]}. {say(12)}" for _ in range(15)]
    twins = [" ".join(w[:k]) + " " + say(9) for w in (say(44).split(), say(44).split()) for k in (44,) for _ in range(4)]
    texts += twins + [t + " " + say(3) for t in twins] + ["short one", "short one", "", None, None] * 2
    data = [(i, t, rng.choice(["en", "de", "fr", "es", "es", None]), f"src{rng.randrange(7)}") for i, t in enumerate(texts)]
    data += [r for r in data if r[0] % 9 == 0]
    schema = "doc_id bigint, text string, lang string, source string"
    for folder, own in (("odd", data), ("apart", [(i, say(9), "en", f"src{i}") for i in range(4)] + [(9, "same. a", "en", "src1"), (10, "same. b", "en", "src2")])):
        path = f"{tmp_path}/{folder}"
        spark.createDataFrame(own, schema).write.parquet(f"{path}/documents.parquet")
        con = duckdb.connect()
        con.execute(f"create view documents as select * from '{path}/documents.parquet/*.parquet'")
        want = sorted(map(repr, con.execute(ORACLES["dup_baselines"]).fetchall()))
        with monkeypatch.context() as m:
            m.setattr(D, "match_by_name", None)
            got = sorted(map(repr, rows(QUERIES["dup_baselines"](spark, path))))
        assert got == want and len(got) == (6 if folder == "odd" else 4), (got, want)


def test_names_are_judged_once_for_all_blocks(spark, monkeypatch):
    """The pairs are those that the judge keeps of all candidates, for repeated words, nulls, long lists of ids and names that differ in order; only distinct names meet."""
    import random

    rng = random.Random(3)
    types = ["ECONOMY", "PROMO", "STANDARD", "MEDIUM", "SMALL", "LARGE", None]
    name = lambda: " ".join(rng.choices("red blue old new big ring bolt".split(), k=rng.randrange(1, 5)))
    data = [(i, i % 4, rng.choice([name(), "red ring", "ring red", "", None]), rng.choice(["B1", "B2", "red"]), rng.choice(types)) for i in range(600)]
    items = spark.createDataFrame(data, "id bigint, catalog_id int, name string, producer string, type string")
    pairs = fresh_path(spark, "bridge")
    D.undirected(D.type_pairs(D.associations(spark), items.select("catalog_id", "type").distinct())).write.parquet(pairs)
    pairs = spark.read.parquet(pairs)
    all_judged = D.judge_named(D.candidates(items, pairs), 0.4).where("verdict = 'same' and not (name_a = name_b and producer_a = producer_b)")
    want = sorted(rows(all_judged.select("a", "b", "cat_a", "cat_b", "rule", "score")))
    monkeypatch.setattr(D, "candidates", None)
    for chunk in (1024, 2):
        assert sorted(rows(D.judged_by_blocks(items, pairs, chunk=chunk))) == want
    assert len(want) > 1000


def test_candidate_sums_are_those_of_the_pairs(spark, small_items):
    items = small_items.union(spark.createDataFrame([(8, 3, None, None, "PROMO"), (9, 0, "n", "p", None)], small_items.schema))
    pairs = D.undirected(D.type_pairs(D.associations(spark), items.select("catalog_id", "type").distinct()))
    want = D.candidates(items, pairs).groupBy("cat_a", "cat_b").agg(F.count("*"), F.sum(F.col("a") + F.col("b")))
    assert sorted(rows(D.candidate_sums(items, pairs))) == sorted(rows(want))


def test_one_to_many_and_fallback(spark, small_items):
    types = spark.createDataFrame([(c, t) for c in range(4) for t in ("ECONOMY", "PROMO", "STANDARD", "MEDIUM", "SMALL", "LARGE")], "catalog_id int, type string")
    got = set(rows(D.type_pairs(D.associations(spark), types)))
    assert {("associated", 0, "ECONOMY", 3, "PROMO"), ("associated", 0, "PROMO", 1, "ECONOMY")} <= {(r, a, x, b, y) for a, x, b, y, r in got}
    back = {y for a, x, b, y, r in got if r == "unassociated" and (a, x, b) == (0, "SMALL", 1)}
    assert back == {"PROMO", "MEDIUM", "SMALL", "LARGE"}  # types of catalogue 1 without association to catalogue 0
    assert not any(r == "associated" and (a, x, b) == (0, "SMALL", 1) for a, x, b, y, r in got)


def test_cascade_properties(spark, sf):
    items = D.items_of(table(spark, sf, "part"))
    dups = rows(D.find_duplicates(items, D.associations(spark)))
    assert all(a < b for a, b, _ in dups)
    named = {x for a, b, s in dups if s == "name" for x in (a, b)}
    assert not any(a in named or b in named for a, b, s in dups if s == "judge")
    assert D.remove_duplicates(items, D.find_duplicates(items, D.associations(spark))).count() == items.count() - len({b for _, b, _ in dups})


def test_blocks_give_the_counts_of_pairs(spark, sf):
    items = D.items_of(table(spark, sf, "part"))
    pairs = D.undirected(D.type_pairs(D.associations(spark), items.select("catalog_id", "type").distinct()))
    made = D.candidates(items, pairs).groupBy("cat_a", "cat_b", "rule").count()
    assert sorted(rows(made)) == sorted(rows(D.candidate_counts(items, pairs)))


def test_composites(spark):
    a, b = " ".join(f"a{chr(97 + i)}x" for i in range(20)), " ".join(f"b{chr(97 + i)}y" for i in range(20))
    docs = spark.createDataFrame([(1, a), (2, b), (3, f"{a} {b}"), (4, f"{a} only one part is held here")], "doc_id bigint, text string")
    assert rows(D.resolve_composites(D.contained_pairs(docs))) == [(3, 2)]


def test_near_text_is_exact(spark, sf):
    docs = table(spark, sf, "documents")
    sh = {r[0]: set(r[1]) for r in rows(docs.select("doc_id", D.shingles(D.tokens(), 5)))}
    want = {(a, b) for a, b in itertools.combinations(sorted(sh), 2) if sh[a] and sh[b] and len(sh[a] & sh[b]) / len(sh[a] | sh[b]) >= 0.7}
    assert {(a, b) for a, b, _ in rows(D.near_text_pairs(docs))} == want


def test_texts_that_share_nothing_leave_no_rows_behind(spark):
    """Shingles of one text only end in the first shuffle; pairs and shares are still those of whole texts."""
    w = [f"{chr(97 + i // 26)}{chr(97 + i % 26)}" for i in range(60)]
    docs = spark.createDataFrame([(1, " ".join(w[:20])), (2, " ".join(w[:19])), (3, " ".join(w[40:])), (4, " ".join(w[:20])), (5, "too short")], "doc_id bigint, text string")
    ranked, copies = D.shared_shingles(docs)
    assert sorted((d, n, len(sh)) for d, n, sh in rows(ranked)) == [(1, 16, 15), (2, 15, 15)]
    assert sorted(rows(copies)) == [(1, 1), (1, 4), (2, 2), (3, 3)]
    assert sorted(rows(D.near_text_pairs(docs))) == [(1, 2, 0.9375), (1, 4, 1.0), (2, 4, 0.9375)]
    assert sorted(rows(D.contained_pairs(docs))) == [(1, 4, 1.0), (2, 1, 1.0), (2, 4, 1.0), (4, 1, 1.0)]


@given(st.lists(st.tuples(st.integers(0, 30), st.integers(0, 30)), max_size=40))
@hyp(max_examples=3, deadline=None)
def test_groups_equal_union_find(spark, edges):
    root = list(range(31))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        root[max(find(a), find(b))] = min(find(a), find(b))
    df = spark.createDataFrame([*edges, (None, 1)], "a bigint, b bigint")
    got = dict(rows(connected_groups(df)))
    assert got == {x: find(x) for x in {y for a, b in edges if a != b for y in (a, b)}}


# calibration


@pytest.mark.parametrize("limit,ceiling,wins,losses", [(12_000, 23_000, 5, 6), (99_000, 23_000, 27, 0)])
def test_ladder_ends_as_told(spark, limit, ceiling, wins, losses):
    grid = P.ladder_grid(spark, tests=1, ceiling=ceiling)
    got = rows(P.run_ladder(grid.withColumn("correct", F.col("level") <= limit)).groupBy("correct").count())
    assert dict(got) == {k: v for k, v in ((True, wins), (False, losses)) if v}


def test_ladder_equals_the_loop(spark):
    trials = P.place_needle(P.ladder_grid(spark), "x").withColumn("needle", F.lit("a b"))
    answers = P.grade_needle(P.simulated_finder(trials, "x"))
    ok = {(r["test"], r["level"], r["attempt"]): r["correct"] for r in answers.collect()}
    want = {(t, *x) for t in range(1, 5) for x in P.run_ladder_sequential(t, lambda t, lv, a: ok[(t, lv, a)])}
    assert set(rows(P.run_ladder(answers).select("test", "level", "attempt", "correct"))) == want


def test_response_identity():
    assert 4 * len(range(10_000, 23_001, 500)) + 21 + 22 == 151


def test_needle_is_planted_whole_and_graded(spark, sf):
    trials = P.place_needle(P.ladder_grid(spark, tests=1, patience=1, ceiling=11_000), "s")
    got = P.plant(trials, P.haystacks(table(spark, sf, "documents"), 1, "s", "en", 11_000), "Foreign needle").collect()
    assert got and all("Foreign needle." in r["text"] and len(r["text"]) == r["level"] + 16 for r in got)
    graded = P.grade_needle(spark.createDataFrame([('{"needle": "a b"}', "a b"), ("no json", "a b"), ('{"needle": "NONE"}', "a b"), ("bare a b", "a b"), (None, "a b")], "raw string, needle string"))
    assert [(r["json_ok"], r["correct"]) for r in graded.collect()] == [(True, True), (False, False), (True, False), (False, True), (False, False)]


# labelling


@pytest.mark.parametrize("scores,want", [((5, 4, 2), {0, 1}), ((3, 3, 1), {0, 1}), ((1, 1, 1), {0, 1, 2})])
def test_selection(spark, scores, want):
    df = spark.createDataFrame([(1, "d", i, s) for i, s in enumerate(scores)], "doc_id int, domain string, label int, score int")
    assert {r["label"] for r in C.select_labels(df).collect()} == want


def test_selection_scope(spark):
    df = spark.createDataFrame([(1, "a", "x", 5), (1, "b", "y", 2), (1, "b", "z", 1)], "doc_id int, domain string, label string, score int")
    assert {r["label"] for r in C.select_labels(df).collect()} == {"x"}
    assert {r["label"] for r in C.select_labels(df, per="domain").collect()} == {"x", "y"}


def test_packing_example(spark):
    df = spark.createDataFrame([(1, i, n) for i, n in enumerate((7000, 7000, 2000, 16000, 100), 1)], "grp int, ord bigint, chars bigint")
    assert [(r["ord"], r["prompt_no"], r["oversize"]) for r in C.pack_prompts(df).orderBy("ord").collect()] == [(1, 1, False), (2, 1, False), (3, 2, False), (4, 3, True), (5, 4, False)]


@pytest.mark.parametrize("n,want", [(8, [4, 4]), (9, [4, 5])])
def test_planner(n, want):
    plan = C.plan_conversations(4, n)
    assert sorted(map(len, plan)) == want and sorted(sum(plan, [])) == list(range(1, n + 1)) and all(len(p) + 5 <= 10 for p in plan)


def test_covering_sets(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = table(spark, sf, "documents"), table(spark, sf, "labels")
    gold = C.gold_labels(docs, labels)
    sets = C.covering_sets(C.dataset_items(docs, labels), gold, "s1").cache()
    assert sets.count() == sets.select("doc_id").distinct().count()
    for r in M.coverage(sets, gold, 8).collect():
        assert r["covered"] == 1.0
    a = sets.where("dataset = 'A'")
    assert a.agg(F.max("pos")).first()[0] == 29
    short = a.where("pos < 29").join(gold, "doc_id").select("domain", "label").distinct().count()
    assert short < 8


# measures

PUBLISHED = [
    ((0.15, 0.81, 0.54), 0.50), ((0.23, 0.90, 0.71), 0.61), ((0.19, 0.57, 0.64), 0.47), ((0.0, 0.54, 0.59), 0.37),
    ((0.83, 0.90, 0.56), 0.76), ((0.71, 0.81, 0.73), 0.75), ((0.26, 0.70, 0.63), 0.53), ((0.70, 0.61, 0.76), 0.68),
]


@pytest.mark.parametrize("domains,total", PUBLISHED)
def test_published_totals_are_means_of_domains(spark, domains, total):
    df = spark.createDataFrame([(1, f"d{i}", f) for i, f in enumerate(domains)], "doc_id int, domain string, f1 double")
    assert M.total_f1(df).first()[0] == pytest.approx(total, abs=0.011)


@pytest.mark.parametrize("empty,want", [("one", 1.0), ("zero", 0.0), ("skip", None)])
def test_item_scores(spark, empty, want):
    s = "doc_id int, domain string, label string"
    gold, pred = spark.createDataFrame([(1, "d", "a"), (1, "d", "b"), (3, "d", "a")], s), spark.createDataFrame([(1, "d", "b"), (1, "d", "c")], s)
    base = spark.createDataFrame([(1, "d"), (2, "d"), (3, "d")], "doc_id int, domain string")
    got = {r["doc_id"]: (r["p"], r["r"], r["f1"]) for r in M.item_scores(gold, pred, base, ["doc_id"], empty).collect()}
    assert got[1] == (0.5, 0.5, 0.5) and got[3] == (0, 0, 0) and got.get(2, (None,))[0] == want


# answers


def test_failures_and_repairs(spark):
    raw = {
        "ok": A.REPEATED, "missing": '{"origin":["germanic, en"],"condition":["clean"]}', "foreign": '{"origin":["martian"],"condition":[],"conduct":[]}',
        "split": '{"origin":["germanic","en"],"condition":["clean"],"conduct":["civil"]}', "inner": '{"origin":["germanic"],"condition":["clean"],"conduct":["civil"]}',
        "key": '{"romance":["fr"],"condition":["clean"],"conduct":["civil"]}', "inverted": '{"clean":["item 1"]}', "text": "I think it is clean",
    }
    df = spark.createDataFrame([("m", 1, i, r) for i, r in enumerate(raw.values())], "model string, run int, doc_id bigint, raw string")
    parsed = A.parse_answers(df)
    reasons = dict(zip(raw, [r["reason"] for r in A.check_validity(parsed).orderBy("doc_id").collect()]))
    assert reasons == {"ok": "none", "missing": "missing key", "foreign": "foreign label", "split": "split label", "inner": "incomplete", "key": "misplaced key", "inverted": "inverted", "text": "not json"}
    once = A.repair(parsed)
    fixed = dict(zip(raw, [(r["reason"], r["origin"]) for r in A.check_validity(once).orderBy("doc_id").collect()]))
    assert fixed["split"] == ("none", ["germanic, en"]) and fixed["key"] == ("none", ["romance, fr"]) and fixed["inner"] == ("incomplete", ["germanic"])
    assert rows(A.repair(once).select("doc_id", "origin", "keys").orderBy("doc_id"))[3] == rows(once.select("doc_id", "origin", "keys").orderBy("doc_id"))[3]


def test_repetition_needs_three(spark):
    df = spark.createDataFrame([("m", 1, i, r) for i, r in enumerate("aabbbc")], "model string, run int, doc_id bigint, raw string")
    assert [r["repeated"] for r in A.repetition_filter(df).orderBy("doc_id").collect()] == [False, False, True, True, True, False]


def test_quality_of_the_pinned_rule(spark):
    sf = "/root/testdata/sf0.01"
    docs = table(spark, sf, "documents").join(table(spark, sf, "labels").select("doc_id"), "doc_id", "left_semi")
    gold = C.gold_labels(table(spark, sf, "documents"), table(spark, sf, "labels"))
    s = M.item_scores(gold, C.select_labels(C.expert_scores(docs)), gold.select("doc_id", "domain").distinct(), ["doc_id"])
    assert M.total_f1(s).first()[0] == pytest.approx(0.9632, abs=0.002)


# extraction, metadata, load


def test_every_offered_element_is_listed():
    assert len(X.ELEMENTS) == 17 and sum(m == "AI" for e in X.ELEMENTS for m in e[1:]) == 3


def test_terms_round_trip(spark):
    old = spark.createDataFrame([(1, f"{MD.OLD}{p}") for p in MD.PROPERTIES], "item_id int, property string")
    up = MD.upgrade_terms(old)
    assert all(r["property"].startswith(MD.NEW) for r in up.collect()) and sorted(rows(MD.downgrade_terms(up))) == sorted(rows(old))


def test_escaping_and_translation(spark):
    df = spark.createDataFrame([(1, '<a> & "b"', "x", "la casa de", "es"), (2, "n", "d", "la de", "fr")], "item_id int, name string, description string, text string, lang string")
    assert MD.render_html(df).first()["html"] == "<article><h1>&lt;a&gt; &amp; &quot;b&quot;</h1><p>x</p></article>"
    assert [(r["translated"], r["replaced"]) for r in MD.translate_text(df, MD.LEXICON).orderBy("item_id").collect()] == [("the casa of", 2), ("la de", 0)]


def test_sync_reaches_the_wish_and_then_rests(spark):
    s = "item_id int, body string, digest string"
    cur, new = spark.createDataFrame([(1, "a", "a"), (2, "b", "b"), (3, "c", "c")], s), spark.createDataFrame([(1, "a", "a"), (2, "B", "B"), (4, "d", "d")], s)
    plan = L.plan_sync(new, cur)
    assert dict(rows(plan)) == {1: "same", 2: "update", 3: "delete", 4: "insert"}
    state = L.apply_sync(cur, new, plan)
    assert sorted(rows(state)) == sorted(rows(new)) and {r["op"] for r in L.plan_sync(new, state).collect()} == {"same"}


def test_portal_hides_its_key_and_counts(spark, tmp_path):
    from catalogflow.sources import portal

    assert "secret" not in repr(portal.PortalWriter({"url": "u", "key": "secret", "dry_run": "false"}))
    with pytest.raises(ValueError):
        portal.PortalWriter({"url": "u", "dry_run": "false"})
    portal.register(spark)
    log = tmp_path / "log.json"
    spark.range(250).write.format("portal").mode("append").option("batch", "100").option("log", str(log)).save()
    assert '"rows": 250' in log.read_text()


def test_icons_seen_and_augmented(spark, sf):
    icons = table(spark, sf, "embeddings")
    got = X.classify_icons(X.icon_variants(icons), icons, ["vec_id", "level"])
    assert got.where("level = 16 and vec_id <> pred_id").count() == 0 and X.augment(icons).count() == 3 * icons.count()
    few = icons.where("vec_id < 60")
    whole, blocks = (X.classify_icons(few, icons, ["vec_id"], limit=n, skip_same=True) for n in (500_000, 10))
    assert sorted(rows(whole)) == sorted(rows(blocks))  # a larger glossary is compared in shuffled blocks


# plans


def plan_of(df):
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def test_plans_have_no_cartesian_product_and_prune(spark, sf):
    from catalogflow.queries import QUERIES

    for name in ("dup_judged", "order_expert_labels", "expert_labels", "needle_passages"):
        assert "CartesianProduct" not in plan_of(QUERIES[name](spark, sf)), name
    p = plan_of(QUERIES["op_filter_predicates"](spark, sf))
    assert "GreaterThanOrEqual(n_chars,500)" in p and "source" not in p.split("ReadSchema")[1].split("\n")[0]


def test_icons_beyond_the_broadcast_bound(spark, sf):
    """A glossary larger than the limit gives the rows that a broadcast one gives."""
    icons = spark.read.parquet(f"{sf}/embeddings.parquet")
    for skip in (False, True):
        some, many = (sorted(map(str, X.classify_icons(icons.union(icons.limit(3)), icons, ["vec_id", "label"], limit, skip).collect())) for limit in (500_000, 10))
        assert some == many and len(some) == icons.count() + 3
    small = X._classify_in_blocks(icons, icons.select("vec_id", "label", F.col("embedding").cast("array<double>").alias("e")), icons.count(), ["vec_id"], True, block_rows=32)
    want = X.classify_icons(icons, icons, ["vec_id"], skip_same=True)
    assert sorted(map(str, small.collect())) == sorted(map(str, want.collect()))


def test_condense_loses_no_document(spark):
    """A best sentence longer than the budget is passed over; where none fits it is cut at a word border; nulls stay."""
    long = "longest words " * 5
    data = [(1, f"{long}.small one. tiny"), (2, long), (3, None), (4, "short. text"), (5, "x" * 50), (6, ". " * 30), (7, "second alpha.b c d e f g h.greatest minds. some others")]
    docs = spark.createDataFrame(data, "doc_id bigint, text string")
    got = {r[0]: r[1:] for r in rows(C.condense(docs, 30))}
    assert got[1] == ("small one. tiny", False) and got[2] == ("longest words longest words", True)
    assert got[3] == (None, False) and got[4] == ("short. text", False) and got[5] == ("x" * 30, True) and got[6] == ("", False)
    assert got[7] == ("second alpha.greatest minds", False) and len(got) == 7


def test_passages_may_begin_and_end_inside_words(spark):
    docs = spark.createDataFrame([(1, "Superheart of the matter is here"), (2, "the heart of the matter is in one two three"), (3, "xone two three four five six sevenx y")], "doc_id bigint, text string")
    bench = spark.createDataFrame([(1, "heart of the matter is"), (2, "one two three four five six seven"), (3, "heart of the matter is in one two three"), (4, ""), (5, None)], "item_id bigint, text string")
    assert {(r["doc_id"], r["item_id"], r["pos"]) for r in P.find_passages(docs, bench).collect()} == {(1, 1, 6), (2, 1, 5), (3, 2, 2), (2, 3, 5)}


def _streamed(spark, parts, schema):
    """A stream that takes one part per batch, in order."""
    import time

    path = fresh_path(spark, "parts")
    for part in parts:
        spark.createDataFrame(part, schema).coalesce(1).write.mode("append").parquet(path)
        time.sleep(0.02)
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def test_funnel_keeps_users_of_all_batches(spark):
    t = "2024-01-0{} 00:00:00".format
    parts = [[(1, 1, t(1), "view"), (2, 2, t(1), "click")], [(3, 1, t(2), "click"), (4, 3, t(2), "view")], [(5, 4, t(3), "view")], [(6, 1, t(4), "purchase"), (7, 2, t(4), "view")]]
    parts = [[(i, u, datetime.fromisoformat(x), k) for i, u, x, k in p] for p in parts]
    got = S.finish(S.funnel(_streamed(spark, parts, "event_id bigint, user_id bigint, ts timestamp, event_type string")), "update", ["user_id"])
    assert {tuple(r) for r in got.select("user_id", "step").collect()} == {(1, 3), (2, 1), (3, 1), (4, 1)}


def test_stream_load_keeps_the_newest_across_batches(spark):
    """A late, older row never replaces a newer one; batches write only the buckets that they touch."""
    parts = [[(1, "new", "d9", 5), (2, "a", "d1", 1)], [(1, "old", "d1", 3), (2, "b", "d2", 2)], [(3, "c", "d1", 1), (1, "tie", "d8", 5)], [(1, "later", "d1", 6)]]
    schema = "item_id bigint, body string, digest string, ts bigint"
    state = fresh_path(spark, "state")
    src = _streamed(spark, parts, schema)
    L.stream_load(src, state, fresh_path(spark, "check"), buckets=8).awaitTermination()
    got = {r["item_id"]: r["body"] for r in L.read_state(spark, state, src.schema).collect()}
    assert got == {1: "later", 2: "b", 3: "c"}
    assert {r["item_id"]: r["body"] for r in L.read_state(spark, state, src.schema, before=3).collect()} == {1: "new", 2: "b", 3: "c"}


def test_groups_that_are_not_finished_are_never_returned(spark):
    chain = spark.createDataFrame([(i, i + 1) for i in range(64)], "a bigint, b bigint")
    with pytest.raises(RuntimeError):
        connected_groups(chain, max_rounds=1)
    assert {r["group_id"] for r in connected_groups(chain).collect()} == {0}
