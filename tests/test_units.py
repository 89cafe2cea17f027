"""Worked examples, invariants and comparisons with brute force."""

from itertools import combinations

import pytest
from pyspark.sql import functions as F

from tabqa.functions.text import mask_text, match_score, normalize_value
from tabqa.operators import deps, expand, family_model, ingest, layout, query, store
from tabqa.plans import answers
from tabqa.session import table
from tabqa.sources import corpus
from tabqa.sources.html_tables import TableParser, extract_tables


def one(spark, column):
    return spark.range(1).select(column.alias("x")).first()["x"]


@pytest.mark.parametrize("text,drop,keep", [("Eng FNU-52X", "ANDA", "ANANDA"), ("", "", ""), ("  ", "", "N"), ("12.5", "DND", "DND"), ("éß٣", "AD", "AD")])
def test_masks(spark, text, drop, keep):
    assert one(spark, mask_text(F.lit(text))) == drop
    assert one(spark, mask_text(F.lit(text), whitespace="keep")) == keep


@pytest.mark.parametrize("text,want", [("n/a", None), (" – ", None), ("008", "8"), ("0", "0"), ("3,5", "3.5"), ("C3", "c3"), ("Two   words", "two words"), (None, None)])
def test_normal_values(spark, text, want):
    assert one(spark, normalize_value(F.lit(text).cast("string"))) == want


def test_fuzzy_beats_none_and_exact_beats_fuzzy(spark):
    for mode, near in (("edit", "maxi"), ("token", "max value"), ("prefix", "maximum")):
        asked = F.lit("max value") if mode == "token" else F.lit("max")
        exact, fuzzy, none = (one(spark, match_score(asked, F.lit(h), mode)) for h in ("max value" if mode == "token" else "max", near if mode != "token" else "value max", "zzz"))
        assert exact == 1 and 0 < fuzzy < 1 and none == 0
    with pytest.raises(ValueError):
        match_score(F.lit("a"), F.lit("b"), tau=0)
    with pytest.raises(ValueError):
        query.Weights(topic=0)


def grid_frame(spark, family, grid):
    return spark.createDataFrame([("t", family, grid)], "table_id string, family string, grid array<array<string>>")


def values(df):
    return [r["values"] for r in df.orderBy("row_no").collect()]


def test_worked_unfolding(spark):
    """Two side and four band cells with a pivot of three: nine columns, one of them noise."""
    spec = expand.FamilySpec("f", data_row=4, data_col=2, side_cols=(0, 1), band_rows=(0, 1, 2, 3), pivot_w=3)
    grid = [["", "", *["T"] * 6], ["", "", *["K"] * 6], ["", "", *["C1"] * 3, *["C2"] * 3], ["", "", "Min", "Nom", "Max"] + ["Min", "Nom", "Max"], ["03", "thin", "1", "2", "3", "n/a", "n/a", "n/a"], ["04", "thick", "4", "5", "6", "7", "8", "9"]]
    flat = values(expand.unfold(grid_frame(spark, "f", grid), expand.family_registry(spark, [spec])))
    assert flat[0] == ["03", "thin", "T", "K", "C1", "Min", "1", "2", "3"]
    assert flat[3] == ["04", "thick", "T", "K", "C2", "Min", "7", "8", "9"] and len(flat) == 4
    assert len(values(expand.unfold(grid_frame(spark, "f", grid), expand.family_registry(spark, [spec]), keep_missing=False))) == 3


def test_unfolding_of_ragged_and_empty_areas(spark):
    grid = [["h", "a", "b", "c"], ["x", "1", "2", "3"]]
    make = lambda ragged: expand.unfold(grid_frame(spark, "f", grid), expand.family_registry(spark, [expand.FamilySpec("f", data_row=1, data_col=1, side_cols=(0,), band_rows=(0,), pivot_w=2, ragged=ragged)]))
    assert values(make("pad")) == [["x", "a", "1", "2"], ["x", "c", "3", None]]
    assert values(make("drop")) == [["x", "a", "1", "2"]]
    with pytest.raises(Exception, match="does not divide"):
        make("error").collect()
    assert values(expand.unfold(grid_frame(spark, "pair_matrix", []), corpus.registry(spark))) == []
    assert values(expand.unfold(grid_frame(spark, "pair_matrix", [["only", "head"]]), corpus.registry(spark))) == []


def test_all_band_cells_can_be_kept(spark):
    spec = expand.FamilySpec("f", data_row=1, data_col=1, side_cols=(0,), band_rows=(0,), pivot_w=2, band_width="all")
    flat = values(expand.unfold(grid_frame(spark, "f", [["", "lo", "hi"], ["x", "1", "2"]]), expand.family_registry(spark, [spec])))
    assert flat == [["x", "lo", "hi", "1", "2"]]


def test_spans_and_broken_html(spark):
    html = "<table><caption>A &amp; B</caption><tr><td rowspan=2>x<td colspan=2>y<tr><td>p<td>q<script>'</table>'</script></table><p>"
    pages = spark.createDataFrame([(1, "u", html), (2, "v", None), (3, "w", "<p>no table"), (4, "z", "<table><tr><td>open")], "page_id long, url string, html string")
    rows = {r["table_id"]: r for r in expand.unspan(extract_tables(pages)).collect()}
    assert rows["u#0"]["grid"] == [["x", "y", "y"], ["x", "p", "q"]] and rows["u#0"]["caption"] == "A & B"
    assert rows["z#0"]["grid"] == [["open"]] and set(rows) == {"u#0", "z#0"}
    nested = "<table><tr><td>a<table><tr><td>b</table>c</table>"
    assert [len(t[1]) for t in TableParser("text").tables(nested)] == [1] and [len(t[1]) for t in TableParser("split").tables(nested)] == [1, 1]


def test_no_change_of_masks_is_no_header(spark):
    grid = grid_frame(spark, "f", [["a", "b"], ["c", "d"], ["e", "f"]])
    assert layout.find_data_start(grid).first()["data_row"] == 0


def test_minimal_keys_against_brute_force(spark, sf):
    for name in ("nation", "customer", "supplier"):
        df = table(spark, sf, name)
        pdf = df.toPandas()
        want = []
        for size in (1, 2, 3):
            want += [c for c in combinations(df.columns, size) if not any(set(k) <= set(c) for k in want) and len(pdf.drop_duplicates(list(c))) == len(pdf)]
        assert sorted(deps.minimal_keys(df, 3)) == sorted(want)
        assert sorted(deps.minimal_keys(df, 3, approx=True)) == sorted(want)


def stage_totals(spark, measure, after=-1):
    """A measure of the stages behind one, summed; older ones may be forgotten meanwhile."""
    held = spark.sparkContext._jsc.sc().statusStore()
    stages = held.stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None).iterator()
    total = 0
    while stages.hasNext():
        stage = stages.next()
        total += getattr(stage, measure)() if stage.stageId() > after else 0
    return total


def last_stage(spark):
    spark.range(1).count()
    stages = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)
    return max(stages.apply(i).stageId() for i in range(stages.size()))


@pytest.mark.parametrize("wished,most", [(2_000_000, 12_000_000), (300, 900), (300, 10)])
def test_keys_of_many_rows_are_found_in_buckets(spark, monkeypatch, wished, most):
    """Nulls, repeated rows and hot values; several buckets, and none that is small enough."""
    monkeypatch.setattr(deps, "BUCKET_VALUES", wished)
    monkeypatch.setattr(deps, "MOST_BUCKET_VALUES", most)
    rows = [(i % 40, i // 40 if i % 3 else None, i % 7, None if i < 90 else i, (i * i) % 11) for i in range(120)]
    df = spark.createDataFrame(rows + rows[:30], "a int, b int, `c c` int, d int, e int")
    told = lambda c: len({tuple(r[i] for i in c) for r in rows}) == len(rows)
    want = [c for size in range(1, 6) for c in combinations(range(5), size) if told(c) and not any(told(x) for n in range(1, size) for x in combinations(c, n))]
    assert deps.minimal_keys_large(df) == [tuple(df.columns[i] for i in c) for c in want]
    assert deps.minimal_keys_large(df, 2) == [tuple(df.columns[i] for i in c) for c in want if len(c) <= 2]
    assert deps.minimal_keys_large(df.where("a < 0")) == [(a,) for a in df.columns]


def test_keys_of_lineitem_do_not_shuffle_rows_for_each_set(spark, sf):
    before = last_stage(spark)
    assert answers.PLANS["keys_lineitem"](spark, sf).count() > 0
    assert 0 < stage_totals(spark, "shuffleWriteRecords", before) < 20 * table(spark, sf, "lineitem").count()


def test_keys_of_tables_with_one_row(spark):
    assert deps.minimal_keys(spark.createDataFrame([(1, 2)], "a int, b int")) == [("a",), ("b",)]


def test_inclusions_are_transitive(spark, sf):
    held = answers.book(spark, sf)
    pairs = {(r["lhs_attr"], r["rhs_attr"]) for r in held.inds.collect()}
    table_of = {r["attr_id"]: r["table_id"] for r in held.attrs.collect()}
    for a, b in pairs:
        for c, d in pairs:
            if b == c and table_of[a] != table_of[d]:
                assert (a, d) in pairs


def test_specs():
    spec = query.parse_query('{"table_topics": ["x"], "targets": ["a"], "conditions": [{"attribute_name": "b", "value": 3}, {"val": "c"}]}')
    assert spec == query.QuerySpec((("b", "3"), (None, "c")), ("a",), ("x",))
    for bad in ("{}", '{"given": []}', '{"given": [{"attr": "a"}]}', '{"given": [{"val": "x"}], "other": 1}'):
        with pytest.raises(ValueError):
            query.parse_query(bad)


def first_pair(spark, sf):
    return corpus.pair_codes(spark, sf).orderBy("brand", "nation").first()


def test_first_is_part_of_all_and_direct_ends_the_search(spark, sf):
    held, pair = answers.book(spark, sf), first_pair(spark, sf)
    spec = {"wanted": ["min"], "given": [{"value": "01"}, {"value": pair["brand"]}, {"value": pair["nation"]}]}
    batch = query.Batch.of(spark, {"q": spec, "d": {"wanted": ["code"], "given": [{"value": pair["brand"]}, {"value": pair["nation"]}]}})
    whole = {(r["query_id"], r["row_id"], r["stage"]) for r in query.answer(held, batch).collect()}
    some = {(r["query_id"], r["row_id"], r["stage"]) for r in query.answer(held, batch, stop="first").collect()}
    assert some <= whole and {s for q, _, s in whole if q == "d"} == {"direct"} and {s for q, _, s in whole if q == "q"} == {"derived"}


def test_more_conditions_never_lower_the_score(spark, sf):
    held = answers.book(spark, sf)
    best = []
    for given in ([{"value": "C2"}], [{"value": "C2"}, {"value": "08"}], [{"value": "C2"}, {"value": "08"}, {"value": "zzzz"}]):
        best.append(query.rank_rows(held, query.Batch.of(spark, {"q": {"given": given}}), k=1).first()["score"])
    assert best[0] <= best[1] <= best[2]


def test_a_suggested_parameter_makes_the_answer_unique(spark, sf):
    held = answers.book(spark, sf)
    code = corpus.limits(spark, sf).orderBy("code", "size_code").first()
    batch = query.Batch.of(spark, {"q": {"wanted": ["max"], "given": [{"value": code["code"]}]}})
    rows = query.answer(held, batch)
    assert [r["attrs"] for r in query.suggest_parameters(held, batch, rows).collect()] == ["Size Code"]
    batch = query.Batch.of(spark, {"q": {"wanted": ["max"], "given": [{"value": code["code"]}, {"attr": "Size Code", "value": code["size_code"]}]}})
    assert query.answer(held, batch).count() == 1


def test_unknown_values_give_nothing(spark, sf):
    assert query.answer(answers.book(spark, sf), query.Batch.of(spark, {"q": {"given": [{"value": "no such value"}]}})).count() == 0


def test_families_are_told_apart(spark, sf):
    folded = family_model.with_folds(answers.grid_features(spark, "/root/testdata/sf0.01")).persist()
    assert folded.where("fold = -1").count() == 19
    assert family_model.holdout_accuracy(folded).first()["accuracy"] >= 0.95
    scores = family_model.cv_scores(folded, ("lindisc", "knn", "gnb"))
    for algorithm in ("lindisc", "gnb"):
        own = [s.accuracy for s in scores if s.algorithm == algorithm]
        assert sum(own) / len(own) >= 0.95
    train, test = folded.where("fold >= 0"), folded.where("fold = -1")
    ours = dict(family_model.predict(test, train, "gnb").collect())
    theirs = dict(family_model._ml_predict(test, train, "gnb", 1).collect())
    assert sum(ours[k] == theirs[k] for k in ours) >= 18
    folded.unpersist()


def test_printed_tables_have_all_minimal_keys_of_any_size(spark):
    """Four parts make one key of the wide table, and a value column is no part of it; the other has a short and a long key."""
    from itertools import product

    wide = [(*r, "v") for r in product("ab", repeat=4)]
    both = [(str(i), *r) for i, r in enumerate(product("ab", repeat=4))]
    cells = [(t, f"{t}{i}", f"a{k}", v) for t, rows in (("wide", wide), ("both", both)) for i, r in enumerate(rows) for k, v in enumerate(r)]
    frame = spark.createDataFrame(cells, "table_id string, row_id string, attr_id string, val_norm string")
    for max_size, want in ((None, {("wide", ("a0", "a1", "a2", "a3")), ("both", ("a0",)), ("both", ("a1", "a2", "a3", "a4"))}), (3, {("wide", ("a0", "a1", "a2", "a3")), ("both", ("a0",))})):
        keys = {}
        for r in deps.minimal_keys_batch(frame, max_size).collect():
            keys.setdefault((r["table_id"], r["key_id"]), []).append(r["attr_id"])
        assert {(t, tuple(sorted(k))) for (t, _), k in keys.items()} == want


def test_long_and_open_spans(spark):
    """A span of many rows is whole; one of 0 goes on to the end of its group of rows, and none goes beyond it."""
    html = "<table><tr><td rowspan=1500>x<td>a" + "".join(f"<tr><td>{i}" for i in range(1600)) + "</table>"
    html += "<table><thead><tr><td rowspan=0>p<td>q<tr><td>r</thead><tbody><tr><td rowspan=9>s<td colspan='2'>t</tbody><tr><td>u</table>"
    pages = spark.createDataFrame([(1, "u", html)], "page_id long, url string, html string")
    grids = {r["table_id"]: r["grid"] for r in expand.unspan(extract_tables(pages)).collect()}
    assert len(grids["u#0"]) == 1601 and grids["u#0"][1499] == ["x", "1498"] and grids["u#0"][1500] == ["1499", None]
    assert grids["u#1"] == [["p", "q", None], ["p", "r", None], ["s", "t", "t"], ["u", None, None]]


def test_large_grids_take_linear_work(spark):
    import time

    grid = [["", "x"] + ["h"] * 58] + [[f"k{i}", str(i)] + [str(i * j) for j in range(58)] for i in range(2000)]
    frame = spark.createDataFrame([("t", grid)], "table_id string, grid array<array<string>>")
    began = time.time()
    found = layout.layout_features(frame).first()
    assert (found["f1"], found["f2"]) == (1.0, 1.0) and time.time() - began < 60
    html = "<table>" + "".join("<tr>" + "".join(f"<td>{i * j}" for j in range(60)) for i in range(2000)) + "</table>"
    again = expand.unspan(extract_tables(spark.createDataFrame([(1, "u", html)], "page_id long, url string, html string"))).first()["grid"]
    assert len(again) == 2000 and again[1999][59] == str(1999 * 59) and time.time() - began < 90


def test_boundaries_against_the_plain_rule():
    import random

    def plain(m, periods, share):
        for i in range(1, len(m)):
            for p in range(1, periods + 1):
                rest = [m[k] == m[k + p] for k in range(i, len(m) - p)]
                if m[i - 1] != m[i] and rest and rest[0] and sum(rest) >= share * len(rest):
                    return i
        return None

    rng = random.Random(4)
    for _ in range(2000):
        masks = [rng.choice("ADN") for _ in range(rng.randint(0, 12))]
        assert layout.first_change(masks, 3, 0.5) == plain(masks, 3, 0.5)
        want = next((i for i in range(1, len(masks)) if masks[i - 1] != masks[i] and masks[i:].count(masks[i]) >= 0.8 * (len(masks) - i)), None)
        assert layout.majority_start(masks, 0.8) == want


def test_similar_texts_are_found_by_grams(spark):
    """No pair within the likeness is missed, whatever the letters; held against all pairs."""
    import random

    rng = random.Random(9)
    texts = sorted({"".join(rng.choice("aab") for _ in range(rng.randint(1, 9))) for _ in range(150)} | {"a" * k for k in range(1, 15)} | {"nation 1", "nation 12", "nations", "station"})
    frame = spark.createDataFrame([(t,) for t in texts], "val_norm string")
    sized = store.sized(frame, F.col("val_norm"))
    asked = frame.withColumnRenamed("val_norm", "asked")
    found = store.similar(asked, sized, store.gram_postings(sized)).withColumn("s", match_score(F.col("asked"), F.col("val_norm"))).where("s > 0")
    pairs = asked.crossJoin(frame).withColumn("s", match_score(F.col("asked"), F.col("val_norm"))).where("s > 0")
    assert sorted(map(tuple, found.collect())) == sorted(map(tuple, pairs.select("asked", "val_norm", "s").collect()))
    assert 0 < sized.where("weak").count() < len(texts) and not sized.where("weak AND val_norm LIKE '%ation%'").count()


def test_too_many_conditions_are_refused(spark):
    spec = {"given": [{"value": str(i)} for i in range(63)]}
    with pytest.raises(ValueError):
        query.parse_query(spec)
    import json

    frame = spark.createDataFrame([("q", json.dumps(spec))], "query_id string, spec string")
    with pytest.raises(Exception, match="at most"):
        query.Batch.of_frame(frame).conditions.collect()
    for bad in ('{"given": []}', '{"given": [{"attr": "a"}]}', "{}"):
        with pytest.raises(Exception, match="needs"):
            query.Batch.of_frame(spark.createDataFrame([("q", bad)], "query_id string, spec string")).conditions.collect()


def test_specs_of_a_frame_are_those_of_the_driver(spark):
    import json

    specs = {"a": {"table_topics": ["x", "y"], "targets": "Max", "conditions": [{"attribute_name": " B ", "value": "08"}, {"val": "c"}]}, "b": {"given": [{"value": "1"}]}}
    ours, theirs = query.Batch.of(spark, specs), query.Batch.of_frame(spark.createDataFrame([(k, json.dumps(v)) for k, v in specs.items()], "query_id string, spec string"))
    for name in ("conditions", "goals", "topics"):
        one, other = getattr(ours, name), getattr(theirs, name)
        assert sorted(map(str, one.collect())) == sorted(map(str, other.select(*one.columns).collect()))


def small_store(spark, tables):
    """A store of tables given as rows with a header."""
    flat, attrs = [], []
    for name, (head, *rows) in tables.items():
        flat += [(name, i, list(map(str, r))) for i, r in enumerate(rows)]
        attrs += [(name, i, label) for i, label in enumerate(head)]
    meta = spark.createDataFrame([(n, "d", n, 1, 1, "plain_listing") for n in tables], "table_id string, doc_id string, caption string, page_begin int, page_end int, family string")
    return store.load_store(spark.createDataFrame(flat, "table_id string, row_no int, values array<string>"), meta, spark.createDataFrame(attrs, "table_id string, ord int, label string"))


def test_parts_read_from_one_table_stand_in_one_row(spark):
    """Both missing parts are read from the same linked table: only pairs that stand in one of its rows are answers."""
    tables = {
        "pairs": [("Left", "Right", "Word"), ("l1", "r1", "go"), ("l2", "r2", "go"), ("l3", "r3", "no")],
        "weights": [("Left", "Right", "Weight"), ("l1", "r1", 11), ("l1", "r2", 12), ("l2", "r1", 21), ("l2", "r2", 22), ("l3", "r3", 33)],
    }
    held = ingest.cataloged(small_store(spark, tables))
    assert [tuple(r) for r in held.composites.where("lhs_table = 'pairs'").orderBy("pos").select("lhs_attr", "rhs_attr", "arity").collect()] == [("pairs#a0", "weights#a0", 2), ("pairs#a1", "weights#a1", 2)]
    batch = query.Batch.of(spark, {"q": {"wanted": ["Weight"], "given": [{"value": "go"}]}})
    weights = lambda s: sorted(r["value"] for r in query.wanted_values(s, batch, query.answer(s, batch).select("query_id", "table_id", "row_id")).collect())
    assert weights(held) == ["11", "22"]
    from dataclasses import replace

    assert weights(replace(held, composites=None)) == ["11", "12", "21", "22"]


def test_dependencies_of_noisy_tables(spark):
    rows = [(i, i // 2, f"x{i // 4}") for i in range(40)]
    noisy = [*rows[:39], (39, 19, "odd")]
    held = small_store(spark, {"clean": [("A", "B", "C"), *rows], "noisy": [("A", "B", "C"), *noisy], "far": [("B",), *((i,) for i in range(19))]})
    fds = lambda **o: {(r["table_id"], r["lhs_attr"][-1], r["rhs_attr"][-1]) for r in deps.find_fds_batch(held.cells, **o).where("n_lhs = 1").collect()}
    assert ("clean", "1", "2") in fds() and ("noisy", "1", "2") not in fds() and ("noisy", "1", "2") in fds(eps=0.05)
    inds = lambda **o: {(r["lhs_attr"], r["rhs_attr"]) for r in deps.unary_inclusions(held.cells, **o).collect()}
    assert ("clean#a1", "far#a0") not in inds() and ("clean#a1", "far#a0") in inds(eps=0.05) and ("far#a0", "clean#a1") in inds()
    twice = small_store(spark, {"t": [("K", "V"), *((min(i, 38), i % 2) for i in range(40))]})
    keys = lambda **o: {r["attr_id"] for r in deps.minimal_keys_batch(twice.cells, **o).where("NOT is_composite").collect()}
    assert keys() == set() and keys(eps=0.05) == {"t#a0"}


def test_wide_tables_say_that_their_search_was_cut(spark, monkeypatch):
    monkeypatch.setattr(deps, "MOST_SETS", 3)
    held = small_store(spark, {"t": [tuple("ABCDE"), *((i & 1, i >> 1 & 1, i >> 2 & 1, i >> 3 & 1, 0) for i in range(16))]})
    keys = deps.minimal_keys_batch(held.cells).collect()
    assert {r["attr_id"] for r in keys} == {f"t#a{i}" for i in range(4)} and not keys[0]["is_complete"] and keys[0]["is_minimal"]


def test_classes_and_circles_of_classes(spark):
    """The store's own classes, and a circle, on which a recursive query wouldn't end."""
    own = {tuple(r) for r in store.class_closure(spark).collect()}
    assert own == {("CompositeKey", "Key"), ("CompositeKey", "Dependency"), ("Key", "Dependency"), ("InclusionDependency", "Dependency"), *((c, c) for c in ("CompositeKey", "Key", "Dependency", "InclusionDependency"))}
    circle = spark.createDataFrame([("a", "b"), ("b", "c"), ("c", "a"), ("d", "a")], "sub string, super string")
    assert {tuple(r) for r in store.class_closure(spark, circle).collect()} == {(x, y) for x in "abcd" for y in "abc"} | {("d", "d")}


def test_names_come_from_the_table_or_the_caption(spark, sf):
    held = answers.ingested(spark, sf)
    named = {}
    for r in held.attrs.collect():
        named.setdefault(r["table_id"].split("/")[-1], set()).add(r["label"])
    assert named["limits#0"] == {"Size Code", "Code", "Min", "Nom", "Max"} and named["zones#0"] == {"Nation", "Zone"} and named["trade#0"] == {"Nation", "Year", "Quantity", "Value"}
    assert {r["family"] for r in held.tables.collect()} == {"limit_matrix", "pair_matrix", "trade_matrix", "plain_listing"}


def test_look_ups_read_the_index(spark, sf):
    """A strict look-up's values reach the scan of the sorted postings."""
    held = answers.book(spark, sf)
    plan = query.hits(held, query.Batch.of(spark, {"q": {"given": [{"value": "c3"}]}}))._jdf.queryExecution().toString()
    assert "EqualTo(val_norm,c3)" in plan or "In(val_norm, [c3])" in plan


def test_equal_values_are_data_and_label_rows_are_not(spark):
    """Limits whose least and greatest are the same everywhere, and a single class, which its caption's names tell from a label row."""
    head = [["", *["Limits"] * 3], ["", *["Class"] * 3], ["", *["C3"] * 3], ["", "Min", "Nom", "Max"]]
    body = [[f"{i:02}", "1", str(20 + i), "50"] for i in range(1, 5)]
    grids = spark.createDataFrame([("limits", "Quantity limits", "limit_matrix", [*head, *body]), ("zones", "Zones", "plain_listing", [["Nation", "Zone"], ["a", "z"], ["b", "z"]])], "table_id string, caption string, family string, grid array<array<string>>")
    registry = corpus.registry(spark)
    flat = expand.unfold(grids, registry)
    names = spark.createDataFrame([("Quantity limits", 0, "Size Code"), ("Quantity limits", 3, "Code")], "caption string, ord int, label string")
    places = lambda given: sorted((r["table_id"], r["ord"], r["label"]) for r in ingest.attributes_of(grids, flat, registry, given).collect())
    data = [("limits", 5, "Min"), ("limits", 6, "Nom"), ("limits", 7, "Max"), ("zones", 0, "Nation"), ("zones", 1, "Zone")]
    assert places(names) == [("limits", 0, "Size Code"), ("limits", 3, "Code"), *data]
    assert places(None) == [("limits", 0, "column_1"), *data]
