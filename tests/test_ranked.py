"""Connectors, folds and ranked answers against nested loops."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from ranked_theta.functions import measures
from ranked_theta.operators import anyk, baselines, connectors, cyclic, equireduce, fold, project, ranked, ranks, stacked
from ranked_theta.operators.cursor import RankedCursor, per_group
from ranked_theta.operators.ranks import dense_rank_domain
from ranked_theta.plans import predicates as P
from ranked_theta.plans.query import Atom, Query, Rank
from ranked_theta.sources.staging import Staging

S = "rid long, a long, b long, g long, w long"
OPS = {"<": lambda x, y: x < y, "<=": lambda x, y: x <= y, ">": lambda x, y: x > y, ">=": lambda x, y: x >= y, "!=": lambda x, y: x != y, "=": lambda x, y: x == y}


def table(spark, rows):
    return spark.createDataFrame(rows, S).repartition(2)


def some(seed, n, low=-6, high=6, null=0.1):
    rng = random.Random(seed)
    value = lambda: None if rng.random() < null else rng.randint(low, high)
    return [(i, value(), value(), rng.randint(0, 1), rng.randint(0, 3)) for i in range(n)]


def holds(term, x, y):
    out = True
    for op, i, j, eps in term:
        u, v = x[i], y[j]
        if u is None or v is None:
            return False
        out &= abs(u - v) < eps if op == "band" else OPS[op](u, v)
    return out


NAMES = {1: "a", 2: "b", 3: "g"}


def condition(terms):
    return P.any_of(*[P.all_of(*[P.Compare(op, P.side(f"s.{NAMES[i]}"), P.side(f"t.{NAMES[j]}"), eps) for op, i, j, eps in t]) for t in terms])


CASES = [
    ([[("<", 1, 1, None)]], ("binary", "median", "multiway")),
    ([[("<=", 1, 2, None)]], ("binary", "median", "multiway")),
    ([[(">", 1, 1, None)]], ("binary", "multiway")),
    ([[(">=", 1, 1, None)]], ("binary", "multiway")),
    ([[("!=", 1, 1, None)]], ("binary", "multiway", "two-way")),
    ([[("band", 1, 1, 3)]], ("binary", "multiway", "two-way")),
    ([[("band", 1, 1, 100)]], ("binary", "multiway")),
    ([[("=", 3, 3, None)]], ("auto",)),
    ([[("=", 3, 3, None), ("<", 1, 1, None), (">=", 2, 2, None)]], ("binary", "multiway")),
    ([[("<", 1, 1, None), ("!=", 2, 2, None), ("band", 1, 2, 4)]], ("binary", "multiway", "two-way")),
    ([[("<", 1, 1, None)], [("<=", 2, 2, None)], [("=", 3, 3, None), ("!=", 1, 2, None)]], ("binary",)),
    ([[("<", 1, 1, None)], [("<", 2, 2, None)]], ("binary",)),
    ([[("=", 3, 3, None), ("<", 1, 1, None)], [("band", 2, 2, 2), (">", 1, 2, None)]], ("binary",)),
]


@pytest.mark.parametrize("terms,methods", CASES)
def test_connectors_and_folds_equal_nested_loops(spark, terms, methods):
    s, t = some(1, 24), some(2, 27)
    expected = sorted((x[0], y[0]) for x in s for y in t if any(holds(term, x, y) for term in terms))
    left, right = table(spark, s), table(spark, t)
    for method in methods:
        graph = equireduce.connector(left, right, condition(terms), method)
        found = sorted(map(tuple, graph.pairs().collect()))
        if graph.dup_factor == 1:
            assert found == expected
        else:
            assert sorted(set(found)) == expected
            assert max((found.count(p) for p in set(found)), default=0) <= graph.dup_factor
    count = dict(map(tuple, equireduce.theta_agg(left, right, condition(terms), "w", "count").collect()))
    least = dict(map(tuple, equireduce.theta_agg(left, right, condition(terms), "w", "min").collect()))
    for x in s:
        mine = [y[4] for y in t if any(holds(term, x, y) for term in terms)]
        assert count.get(x[0], 0) == len(mine)
        assert least.get(x[0]) == (min(mine) if mine else None)


def test_key_ranges_change_nothing(spark):
    s, t = table(spark, some(3, 60, -50, 50)), table(spark, some(4, 60, -50, 50))
    for where in (P.lt("s.a", "t.b"), P.ge("s.a", "t.b"), P.ne("s.a", "t.b"), P.eq("s.g", "t.g") & P.lt("s.a", "t.b")):
        for fn in ("min", "sum"):
            one = sorted(map(tuple, equireduce.theta_agg(s, t, where, "w", fn).collect()))
            cut = sorted(map(tuple, equireduce.theta_agg(s, t, where, "w", fn, ranges=7).collect()))
            assert one == cut


def test_terms_that_exclude_each_other_count_each_pair_once():
    terms = [[("=", 3, 3, None), ("<", 1, 1, None)], [("=", 3, 3, None), (">=", 2, 2, None)], [("!=", 1, 2, None)]]
    made = fold.disjoint([[(P.Compare(op, P.side(f"s.{NAMES[i]}"), P.side(f"t.{NAMES[j]}")), NAMES[i], NAMES[j]) for op, i, j, _ in t] for t in terms])
    s, t = some(5, 30, null=0), some(6, 30, null=0)
    where = {v: k for k, v in NAMES.items()}
    for x in s:
        for y in t:
            hit = sum(all(OPS[p.op](x[where[a]], y[where[b]]) for p, a, b in term) for term in made)
            assert hit == any(holds(term, x, y) for term in terms)


def test_large_k_goes_through_nodes(spark, monkeypatch):
    monkeypatch.setattr(ranked, "SMALL_K", 3)
    tables = [some(70 + i, 12) for i in range(3)]
    query, joins = path_query(spark, tables, Rank.sum())
    every = brute(tables, joins, Rank.sum(), 10**6)
    for k in (5, 40, len(every) + 1):
        assert [(r["weight"], (r["rid_1"], r["rid_2"], r["rid_3"])) for r in ranked.top_k(query, k).orderBy("rank").collect()] == every[:k]
    either = Query([Atom("s", table(spark, tables[0])), Atom("t", table(spark, tables[1]))], P.lt("s.a", "t.a") | P.gt("s.b", "t.b"))
    expected = sorted((x[4] + y[4], (x[0], y[0])) for x in tables[0] for y in tables[1] if holds([("<", 1, 1, None)], x, y) or holds([(">", 2, 2, None)], x, y))
    assert [(r["weight"], (r["rid_1"], r["rid_2"])) for r in ranked.top_k(either, 30).orderBy("rank").collect()] == expected[:30]
    g = stacked.stack(either, "binary")
    assert g.duplicates == 2 and list(stacked.walk(g, 30)) == expected[:30]


def test_hot_groups_are_cut_into_ranges(spark, monkeypatch):
    monkeypatch.setattr(fold, "SPLIT", 10)
    s, t = [(i, i % 37, -i, 0, i % 5) for i in range(120)], [(i, i * 7 % 41, i, 0, i % 3) for i in range(120)]
    where = P.eq("s.g", "t.g") & P.lt("s.a", "t.a")
    found = equireduce.theta_agg(table(spark, s), table(spark, t), where, "w", "sum")
    assert dict(map(tuple, found.collect())) == {x[0]: total for x in s if (total := sum(y[4] for y in t if x[1] < y[1])) or any(x[1] < y[1] for y in t)}
    plan = found._jdf.queryExecution().toString()
    assert "_b" in plan  # ranges are partition keys of the running aggregates


def test_best_of_each_group_in_one_pass(spark):
    tables = [some(80 + i, 14) for i in range(2)]
    query = Query([Atom(f"t{i}", table(spark, r)) for i, r in enumerate(tables)], P.lt("t0.a", "t1.b"))
    got = sorted((r["group_key"], r["rank"], r["weight"], r["rid_1"], r["rid_2"]) for r in per_group(query, "g", 4).collect())
    expected = []
    for g in (0, 1):
        mine = sorted((x[4] + y[4], x[0], y[0]) for x in tables[0] for y in tables[1] if x[3] == y[3] == g and holds([("<", 1, 2, None)], x, y))[:4]
        expected += [(g, i + 1, *one) for i, one in enumerate(mine)]
    assert got == expected


def test_chain_paths_are_the_joining_pairs(spark):
    for op, seeds in (("<", (1, 2)), (">=", (3, 4))):
        s, t = some(seeds[0], 20), some(seeds[1], 20)
        graph = equireduce.connector(table(spark, s), table(spark, t), condition([[(op, 1, 2, None)]]), "chain")
        first, step, last = (sorted(map(tuple, p.collect())) for p in graph.parts)
        steps = dict(step)
        found = []
        for rid, node in first:
            while node is not None:
                found += [(rid, r) for n, r in last if n == node]
                node = steps.get(node)
        assert sorted(found) == sorted((x[0], y[0]) for x in s for y in t if holds([(op, 1, 2, None)], x, y))


def test_repeated_answers_are_dropped_by_weight():
    stream = [(1, (1, 2)), (1, (1, 2)), (1, (1, 3)), (2, (1, 2)), (2, (4, 4)), (2, (1, 2))]
    assert list(stacked.dedupe(stream)) == [(1, (1, 2)), (1, (1, 3)), (2, (1, 2)), (2, (4, 4))]


def test_roots_selections_and_sizes(spark):
    small, large = [(i, i % 9, i % 7, i % 2, i) for i in range(12)], [(i, i % 9, i % 7, i % 2, i) for i in range(80)]
    query = Query([Atom("x", table(spark, large)), Atom("y", table(spark, small))], P.band("x.a", "y.b", 3) & P.gt("x.b", P.const("x", 2)))
    from ranked_theta.plans import statistics

    assert statistics.choose_root(query.routed()) == "y"  # a band asks each source in three cells
    expected = sorted((x[4] + y[4], x[0], y[0]) for x in large for y in small if abs(x[1] - y[2]) < 3 and x[2] > 2)[:20]
    for root in (None, "auto"):
        assert [(r["weight"], r["rid_1"], r["rid_2"]) for r in ranked.top_k(query, 20, root=root).orderBy("rank").collect()] == expected
    graph = equireduce.connector(table(spark, small), table(spark, small), P.lt("s.a", "t.a"), "binary")
    assert len(graph.layers()) == graph.depth + 1
    held = {(r["variant"], r["k"]): r["listed"] + r["candidates"] for r in measures.memory(Query([Atom("x", table(spark, small)), Atom("y", table(spark, small))], P.lt("x.a", "y.a")), [1, 20], ["lazy", "all"], spark).collect()}
    assert held["lazy", 1] <= held["lazy", 20] <= held["all", 20] + 1000


def test_cycles_of_four(spark):
    tables = [some(60 + i, 7) for i in range(4)]
    where = P.all_of(*[P.lt(f"t{i}.a", f"t{(i + 1) % 4}.b") for i in range(4)])
    query = Query([Atom(f"t{i}", table(spark, r)) for i, r in enumerate(tables)], where)
    expected = brute(tables, [(i, (i + 1) % 4, [("<", 1, 2, None)]) for i in range(4)], Rank.sum(), 25)
    got = [(r["weight"], tuple(r[f"rid_{i}"] for i in range(1, 5))) for r in cyclic.cyclic_ranked(query, 25).orderBy("rank").collect()]
    assert got == expected


def test_dense_ranks(spark):
    values = spark.createDataFrame([(v,) for v in (5, 1, 1, None, 9, 7, 5)], "v long")
    ranks, n = dense_rank_domain(values, "v", Staging(spark, "test"), "x")
    assert n == 4 and dict(map(tuple, ranks.collect())) == {1: 0, 5: 1, 7: 2, 9: 3}


def test_chain_is_not_layered(spark):
    graph = equireduce.connector(table(spark, some(1, 9)), table(spark, some(2, 9)), P.lt("s.a", "t.a"), "chain")
    with pytest.raises(ValueError):
        graph.pairs()


def test_empty_sides(spark):
    full, empty = table(spark, some(1, 5)), table(spark, [])
    for a, b in ((full, empty), (empty, full), (empty, empty)):
        assert equireduce.theta_join(a, b, P.lt("s.a", "t.a")).count() == 0
        query = Query([Atom("x", a), Atom("y", b)], P.lt("x.a", "y.a"))
        assert ranked.top_k(query, 3).count() == 0
        assert ranked.count_answers(query).first()[0] == 0


def brute(tables, joins, rank, k):
    found = []
    for rows in itertools.product(*tables):
        if any(r[4] is None for r in rows) or not all(holds(term, rows[i], rows[j]) for i, j, term in joins):
            continue
        found.append((sum(r[4] for r in rows), tuple(r[0] for r in rows)))
    return sorted(found, key=lambda x: (-x[0] if rank.desc else x[0], x[1]))[:k]


def path_query(spark, tables, rank):
    n = len(tables)
    where = P.all_of(*[P.eq(f"t{i}.g", f"t{i + 1}.g") & P.lt(f"t{i}.a", f"t{i + 1}.b") for i in range(n - 1)])
    joins = [(i, i + 1, [("=", 3, 3, None), ("<", 1, 2, None)]) for i in range(n - 1)]
    return Query([Atom(f"t{i}", table(spark, r)) for i, r in enumerate(tables)], where, rank), joins


def test_top_k_with_ties_everywhere_and_ends(spark):
    tables = [some(10 + i, 12) for i in range(3)]
    for rank in (Rank.sum(), Rank.sum(True)):
        query, joins = path_query(spark, tables, rank)
        every = brute(tables, joins, rank, 10**6)
        for k in (0, 1, 7, len(every) + 1):
            got = [(r["weight"], (r["rid_1"], r["rid_2"], r["rid_3"])) for r in ranked.top_k(query, k).orderBy("rank").collect()]
            assert got == every[:k]
        assert ranked.count_answers(query).first()[0] == len(every)


def test_branching_tree_from_any_root(spark):
    tables = [some(20 + i, 9) for i in range(4)]
    joins = [(0, 1, [("<", 1, 1, None)]), (0, 2, [("=", 3, 3, None), (">", 1, 2, None)]), (2, 3, [("!=", 2, 2, None)])]
    where = P.all_of(P.lt("t0.a", "t1.a"), P.eq("t0.g", "t2.g"), P.gt("t0.a", "t2.b"), P.ne("t2.b", "t3.b"))
    query = Query([Atom(f"t{i}", table(spark, r)) for i, r in enumerate(tables)], where)
    expected = brute(tables, joins, Rank.sum(), 40)
    for root in ("t0", "t3"):
        got = [(r["weight"], tuple(r[f"rid_{i}"] for i in range(1, 5))) for r in ranked.top_k(query, 40, root=root).orderBy("rank").collect()]
        assert got == expected


def test_cursor_and_enumerators_agree(spark):
    tables = [some(30 + i, 10) for i in range(3)]
    query, joins = path_query(spark, tables, Rank.sum())
    every = brute(tables, joins, Rank.sum(), 10**6)
    cursor = RankedCursor(query, first=4)
    pages = [*cursor.next(3), *cursor.next(5), *cursor.next(10**4)]
    assert [(r["weight"], (r["rid_1"], r["rid_2"], r["rid_3"])) for r in pages] == every
    assert cursor.next(1) == []
    for method in ("binary", "multiway"):
        instance = stacked.instance(stacked.stack(query, method), len(every) + 5)
        for variant in anyk.VARIANTS:
            assert [(w, tuple(ids)) for w, ids in anyk.enumerate_answers(instance, variant)] == every


def test_cycles_and_baselines(spark):
    tables = [some(40 + i, 8) for i in range(3)]
    where = P.all_of(P.lt("t0.a", "t1.b"), P.lt("t1.a", "t2.b"), P.lt("t2.a", "t0.b"))
    query = Query([Atom(f"t{i}", table(spark, r)) for i, r in enumerate(tables)], where)
    expected = brute(tables, [(0, 1, [("<", 1, 2, None)]), (1, 2, [("<", 1, 2, None)]), (2, 0, [("<", 1, 2, None)])], Rank.sum(), 30)
    for run in (cyclic.cyclic_filter, cyclic.cyclic_ranked, baselines.materialize_rank):
        got = [(r["weight"], (r["rid_1"], r["rid_2"], r["rid_3"])) for r in run(query, 30).orderBy("rank").collect()]
        assert got == expected
    path, joins = path_query(spark, tables, Rank.sum())
    expected = brute(tables, joins, Rank.sum(), 15)
    for run in (baselines.direct_equi, baselines.native_sql):
        got = [(r["weight"], (r["rid_1"], r["rid_2"], r["rid_3"])) for r in run(path, 15).orderBy("rank").collect()]
        assert got == expected
    assert project.is_free_connex(path, ["t0", "t1"]) and not project.is_free_connex(path, ["t0", "t2"])


def test_plans_of_theta_joins_have_no_nested_loop(spark):
    s, t = table(spark, some(1, 20)), table(spark, some(2, 20))
    pairs = equireduce.theta_join(s, t, P.lt("s.a", "t.a"), "binary")
    plan = pairs._jdf.queryExecution().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan


@pytest.mark.parametrize("method", ["binary", "median", "multiway", "two-way"])
def test_edges_are_never_broadcast(spark, method):
    s, t = table(spark, some(1, 20)), table(spark, some(2, 20))
    for where in (P.lt("s.a", "t.a"), P.band("s.a", "t.a", 3) & P.ne("s.b", "t.b")):
        plan = equireduce.theta_join(s, t, where, method)._jdf.queryExecution().toString()
        assert "SortMergeJoin" in plan and "Broadcast" not in plan


def test_ranks_of_exploded_rows_are_never_broadcast(spark):
    s, t = table(spark, some(1, 20)), table(spark, some(2, 20))
    wide = connectors.cells(s.withColumn("a", F.col("a") * 10**9), "a", 10**10, True, "_c").withColumn("_v", F.col("_c.v"))
    other = connectors.cells(t.withColumn("a", F.col("a") * 10**9), "a", 10**10, False, "_c").withColumn("_v", F.col("_c.v"))
    for coded in ranks.codes(wide, other, "_v", "_v", Staging(spark, "test"), "codes")[:2]:
        assert "Broadcast" not in coded._jdf.queryExecution().toString()


def test_ranges_of_exploded_rows_are_never_broadcast(spark):
    rows = table(spark, some(1, 20, null=0)).select(*[F.lit(1).alias("_q0"), F.col("a").alias("_k"), (F.col("rid") % 2).alias("_src"), F.when(F.col("rid") % 2 == 0, F.col("w")).alias("_val")])
    assert "Broadcast" not in fold._running(rows, ["_q0"], "<", "sum", 4)._jdf.queryExecution().toString()


@pytest.mark.parametrize("method", ["binary", "median", "multiway"])
def test_pairs_of_a_large_node_are_dealt_over_tasks(spark, monkeypatch, method):
    """Also a row without id keeps its pairs, and columns that the last edges carry stay with theirs."""
    for name, value in (("DENSE", 2), ("BUNDLE", 8), ("GATHERED", 40), ("PAIRS", 1 << 26)):
        monkeypatch.setattr(connectors, name, value, raising=False)
    s, t = ([(None if i == 7 else i, i * step % 64) for i in range(n)] for n, step in ((150, 5), (210, 11)))
    for op, less in ((P.lt, lambda x, y: x < y), (P.le, lambda x, y: x <= y)):
        got = equireduce.theta_join(*[spark.createDataFrame(r, "rid long, a long").repartition(2) for r in (s, t)], op("s.a", "t.a"), method)
        tasks = {r["p"]: r["count"] for r in got.groupBy(F.spark_partition_id().alias("p")).count().collect()}
        expected = [(x[0], y[0]) for x in s for y in t if less(x[1], y[1])]
        key = lambda pair: tuple((x is None, x or 0) for x in pair)
        assert sorted(map(tuple, got.collect()), key=key) == sorted(expected, key=key)
        assert len(tasks) > 1 and max(tasks.values()) < 0.45 * len(expected)
    edges = [(i % 3, i, i * 10) for i in range(90)]
    graph = connectors.Connector([spark.createDataFrame([(x, n) for n, x, _ in edges], "rid_s long, node long"), spark.createDataFrame(edges, "node long, rid_t long, w long")], 2, 1)
    assert sorted(map(tuple, graph.pairs(("w",)).collect())) == sorted((x, y, w) for n, x, _ in edges for m, y, w in edges if n == m)


@pytest.mark.parametrize("method", ["binary", "median", "multiway", "two-way"])
def test_last_comparisons_are_split_over_sorted_ends(spark, monkeypatch, method):
    """A row without id keeps its pairs, bundles and gathered ends are small, and columns that are carried stay with theirs."""
    for name, value in (("BUNDLE", 4), ("GATHERED", 24)):
        monkeypatch.setattr(connectors, name, value)
    s, t = ([(None if i == 7 else i, i * step % 31, None if i % 13 == 0 else i * 7 % 19, i) for i in range(n)] for n, step in ((70, 5), (90, 11)))
    left, right = (spark.createDataFrame(r, "rid long, a long, b long, w long").repartition(2) for r in (s, t))
    full = lambda joins: lambda x, y: None not in (x[2], y[2]) and joins(x, y)
    wheres = [(P.lt("s.a", "t.a") & P.Compare(op, P.side("s.b"), P.side("t.b")), full(lambda x, y, op=op: x[1] < y[1] and OPS[op](x[2], y[2]))) for op in ("<=", ">", "!=")]
    wheres.append((P.all_of(P.le("s.a", "t.a"), P.ge("s.b", "t.a"), P.lt("s.w", "t.w")), lambda x, y: x[2] is not None and x[1] <= y[1] <= x[2] and x[3] < y[3]))
    key = lambda pair: tuple((v is None, v or 0) for v in pair)
    for where, joins in wheres:
        got = equireduce.theta_join(left, right, where, method)
        assert sorted(map(tuple, got.collect()), key=key) == sorted([(x[0], y[0]) for x in s for y in t if joins(x, y)], key=key)
    graph = equireduce.connector(left, right, P.band("s.a", "t.a", 6) & P.ge("s.b", "t.b"), method)
    assert graph.ends is not None
    graph.carry(right.select(F.col("rid").alias("rid_t"), "w").where("rid is not null"))
    expected = [(x[0], y[0], y[3]) for x in s for y in t if None not in (x[2], y[2], y[0]) and abs(x[1] - y[1]) < 6 and x[2] >= y[2]]
    assert sorted(map(tuple, graph.pairs(("w",)).collect()), key=key) == sorted(expected, key=key)


def test_nodes_of_two_bounds_are_only_where_pairs_can_be(spark):
    """Few edges, and the same pairs by them as by the bundles."""
    s, t = some(80, 200, 0, 1000, null=0), some(81, 200, 0, 1000, null=0)
    graph = equireduce.connector(table(spark, s), table(spark, t), P.band("s.a", "t.a", 40) & P.lt("s.b", "t.b"), "two-way")
    assert sum(p.count() for p in graph.parts) < 0.6 * 400 * 5**3
    bare = connectors.Connector(graph.parts, graph.depth, graph.dup_factor)
    expected = sorted((x[0], y[0]) for x in s for y in t if abs(x[1] - y[1]) < 40 and x[2] < y[2])
    assert sorted(map(tuple, bare.pairs().collect())) == sorted(map(tuple, graph.pairs().collect())) == expected


def test_terms_that_exclude_each_other_need_no_distinct(spark):
    s, t = some(1, 24), some(2, 27)
    full = [[r for r in rows if None not in r] for rows in (s, t)]
    for some_s, some_t, apart in ((full[0], full[1], True), (s, t, False)):
        got = equireduce.theta_join(table(spark, some_s), table(spark, some_t), P.lt("s.a", "t.a") | P.lt("s.b", "t.b"), "multiway")
        less = lambda x, y, c: x[c] is not None and y[c] is not None and x[c] < y[c]
        assert sorted(map(tuple, got.collect())) == sorted((x[0], y[0]) for x in some_s for y in some_t if less(x, y, 1) or less(x, y, 2))
        assert ("Deduplicate [rid_s" in got._jdf.queryExecution().analyzed().toString()) != apart
    graph = equireduce.connector(table(spark, s), table(spark, t), P.ne("s.a", "t.a") & P.band("s.b", "t.b", 2), "two-way")
    assert graph.dup_factor == 1


def test_counts_beyond_64_bits_are_exact(spark):
    rows = spark.createDataFrame([(i, 1, 1) for i in range(4096)], "rid long, a long, w long").repartition(2)
    atoms = [Atom(f"t{i}", rows) for i in range(6)]
    found = ranked.count_answers(Query(atoms, P.all_of(*[P.eq(f"t{i}.a", f"t{i + 1}.a") for i in range(5)])))
    assert int(found.first()["answers"]) == 4096**6 > 1 << 63


def test_walks_stack_no_more_than_k_rows(spark, monkeypatch):
    tables = [some(50 + i, 30) for i in range(3)]
    stacked_rows, build = [], connectors.build

    def counted(left, right, *rest):
        stacked_rows.extend((left.count(), right.count()))
        return build(left, right, *rest)

    monkeypatch.setattr(connectors, "build", counted)
    query, joins = path_query(spark, tables, Rank.sum())
    got = stacked.any_k(query, 7, "recursive").orderBy("rank").collect()
    assert [(r["weight"], (r["rid_1"], r["rid_2"], r["rid_3"])) for r in got] == brute(tables, joins, Rank.sum(), 7)
    assert len(stacked_rows) == 4 and max(stacked_rows) <= 7
    with pytest.raises(ValueError):
        stacked.instance(stacked.stack(query, k=3), 4)


def test_native_sql_says_the_cells_of_a_band(spark):
    tables = [some(60, 40, -20, 20), some(61, 40, -20, 20)]
    query = Query([Atom(f"t{i}", table(spark, r)) for i, r in enumerate(tables)], P.band("t0.a", "t1.b", 7) & P.ne("t0.b", "t1.a"))
    expected = brute(tables, [(0, 1, [("band", 1, 2, 7), ("!=", 2, 1, None)])], Rank.sum(), 10**6)
    for cached in (False, True):
        found = baselines.native_sql(query, 10**6, cached)
        assert [(r["weight"], (r["rid_1"], r["rid_2"])) for r in found.orderBy("rank").collect()] == expected
    plan = baselines.native_sql(query, 10)._jdf.queryExecution().toString()
    assert "SortMergeJoin" in plan and "NestedLoop" not in plan and "Cartesian" not in plan


@pytest.mark.parametrize("method", ["binary", "direct"])
def test_listed_answers_are_never_joined_with_broadcast_rows(spark, method):
    tables = [some(70 + i, 12) for i in range(3)]
    query, joins = path_query(spark, tables, Rank.sum())
    found = equireduce.enumerate_all(query, method)
    got = sorted((r["weight"], (r["rid_1"], r["rid_2"], r["rid_3"])) for r in found.collect())
    assert got == sorted(brute(tables, joins, Rank.sum(), 10**6))
    if method == "binary":
        assert "Broadcast" not in found._jdf.queryExecution().toString()


def test_partners_of_a_row_come_in_arrays(spark):
    """Pairs are far more than the rows that hold them, and an array whose elements join a further atom becomes rows."""
    s, t = some(90, 80, null=0), some(91, 80, null=0)
    graph = equireduce.connector(table(spark, s), table(spark, t), P.lt("s.a", "t.a") & P.ne("s.b", "t.b"), "binary")
    fans = graph.fans().collect()
    expected = sorted((x[0], y[0]) for x in s for y in t if x[1] < y[1] and x[2] != y[2])
    assert sorted((r["rid_s"], one) for r in fans for one in r["fan"]["rid_t"]) == expected and 3 * len(fans) < len(expected)
    tables = [some(92 + i, 8) for i in range(4)]
    query, joins = path_query(spark, tables, Rank.sum())
    got = sorted((r["weight"], tuple(r[f"rid_{i + 1}"] for i in range(4))) for r in equireduce.enumerate_all(query, "binary").collect())
    assert got == sorted(brute(tables, joins, Rank.sum(), 10**6))
