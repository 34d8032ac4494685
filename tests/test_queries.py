"""Registered queries against SQL on the smallest tables."""

import pytest
from compare import same_rows

from textfactor import catalog as queries

#: Sweeps that take long; their kernels are tested on their own, and the queries are compared with their SQL outside of these tests.
SLOW = {"edit_distance_methods", "edit_anchor_test", "lz_grid_sizes_tau8_merged", "lz_grid_sizes_tau4_sqrt_product", "lz_grid_sizes_tau2_merged", "lz_grid_sizes_tau1_merged", "lz77_engines"}


@pytest.mark.parametrize("name", [n for n in queries.ORACLES if n not in SLOW])
def test_against_sql(spark, duck, sf, name):
    assert same_rows(queries.QUERIES[name](spark, sf).toPandas(), duck.sql(queries.ORACLES[name]).df()) == ""


def test_names_without_clash():
    assert set(queries.ORACLES) <= set(queries.QUERIES)


def test_injected_edits_bound_the_distance(spark, sf):
    assert queries.QUERIES["edit_injected_k4"](spark, sf).where("distance > 4").count() == 0


def test_long_text_equals_kernel(spark, sf):
    from textfactor.kernels import apps, lz, suffix
    from textfactor.operators import long_text
    from textfactor.sources import tables

    flags = tables.flag_text(spark, sf).where("pos < 1500").cache()
    syms = [r.sym for r in flags.orderBy("pos").collect()]
    codes = [sorted(set(syms)).index(s) for s in syms]
    order = suffix.SuffixOrder(codes)
    ranks = long_text.suffix_ranks(flags)
    assert [r["rank"] for r in ranks.orderBy("pos").collect()] == order.isa.tolist()
    assert [r.start for r in long_text.lyndon_starts(ranks).orderBy("start").collect()] == [a for a, _ in apps.lyndon(codes)]
    assert long_text.runs_table(long_text.bwt_table(ranks)).count() == suffix.run_count(codes)
    got = [(r.start, r.len) for r in long_text.lz77_lengths(flags, block=128).orderBy("start").collect()]
    assert got == [p[:2] for p in lz.lz77(codes)]


def test_plans(spark, sf):
    from textfactor.operators import columns, joins
    from textfactor.plans.rewrite import plan_text
    from textfactor.sources import tables

    texts = tables.short_texts(spark, sf)
    runs = columns.bwt_run_rows(texts, "t", ["id"])
    plan = plan_text(joins.range_join(columns.bwt_rows(texts, "t", ["id"]), "rank", runs.drop("bwt"), "row_start", "row_end", 16, ("id",)))
    assert "NestedLoop" not in plan and "CartesianProduct" not in plan
    scan = plan_text(tables.table(spark, sf, "documents").where("lang = 'en'").select("doc_id"))
    assert "PushedFilters: [IsNotNull(lang), EqualTo(lang,en)]" in scan and "text" not in scan.split("ReadSchema")[1].split("\n")[0]


def test_entry_works_without_optional_parts(spark, sf):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert "edit_distance_methods" in __spark_entry__.queries()


def test_near_copies_by_brute_force(spark, sf, tmp_path):
    from textfactor import workload_queries as w

    head = "the same first words, then "
    texts = {0: head + "a b c d", 1: head + "a b x d", 2: head + "q" * 200, 3: "another", 4: head + "a b c d", 5: None}
    spark.createDataFrame(list(texts.items()), "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    got = {(r.a_id, r.b_id): r.distance for r in w.near_copy_distances(spark, str(tmp_path)).collect()}
    assert got == w.brute_near_copies({k: v for k, v in texts.items() if v is not None})
    assert all(r.agree for r in w.near_copy_distances(spark, str(tmp_path)).collect())
    assert {(r.a_id, r.b_id) for r in w.near_copy_matches(spark, str(tmp_path)).collect()} == set(got)


def test_bucketed_table_joins_without_shuffle(spark, sf):
    from textfactor.plans.rewrite import plan_text
    from textfactor.sources import tables

    for name, key in (("tf_orders", "o_orderkey"), ("tf_lines", "l_orderkey")):
        source = {"tf_orders": "orders", "tf_lines": "lineitem"}[name]
        tables.write_bucketed(tables.table(spark, sf, source).select(key), name, key, 4)
    joined = spark.table("tf_orders").join(spark.table("tf_lines").hint("merge"), spark.table("tf_orders").o_orderkey == spark.table("tf_lines").l_orderkey)
    assert "Exchange" not in plan_text(joined) and joined.count() == tables.table(spark, sf, "lineitem").join(tables.table(spark, sf, "orders"), tables.F.expr("o_orderkey = l_orderkey")).count()


def test_count_filter_loses_no_pair(spark, sf):
    from textfactor.operators import joins
    from textfactor.sources import tables

    names = tables.table(spark, sf, "part").groupBy("p_name").agg(tables.F.min("p_partkey").alias("p_partkey"))
    plain, counted = (joins.similarity_join(names, names, "p_partkey", "p_partkey", "p_name", "p_name", 3, self_join=True, count_q=q) for q in (None, 2))
    assert sorted(map(tuple, plain.collect())) == sorted(map(tuple, counted.collect()))
