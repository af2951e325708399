"""Spark-side operators against brute force and golden counts."""

import pytest
from pyspark.sql import functions as F

from patternspark.functions import bits
from patternspark.operators import condense, constraints, encode, freqsat, measure
from patternspark.operators.frontier import mine_growing_frontier
from patternspark.operators.itemdb import absolute, build_item_db, profile
from patternspark.operators.solver import OutOfBudget
from patternspark.plans.advisor import choose_formulation, recommend
from patternspark.plans.mine import Coverage, Frequency, Model, MustContain, is_satisfiable, mine
from patternspark.session import cut
from patternspark.sources import databases as D
from patternspark.sources.bins import Bins
from patternspark.sources.generator import generate


@pytest.fixture(scope="module")
def illus(spark):
    return D.item_db(spark, "", "illus")


def sets(result):
    return {r.itemset: r.sup for r in result.patterns.collect()}


def test_worked_example(spark, illus):
    got = {(r.itemset, r.tid) for r in measure.coverage(D.illus(spark), ["J,N"]).collect()}
    assert got == {("J,N", 4), ("J,N", 5)}
    r = measure.patterns(measure.support(illus, measure.candidates(illus, ["J,N"])), illus).first()
    assert (r.sup, r.freq) == (2, 0.333333)


@pytest.mark.parametrize("theta,counts", [(1, (177, 16, 5)), (2, (56, 11, 4)), (3, (13, 7, 4)), (4, (3, 3, 3))])
def test_golden_counts(illus, theta, counts):
    fr = mine(illus, theta, output="frequent").masks
    p = condense.border_profile(fr, illus).first()
    assert (p.n_frequent, p.n_closed, p.n_maximal) == counts


def test_golden_members(illus):
    assert sets(mine(illus, 3)) == {"A,N": 3, "E,N": 3, "H,N": 3, "D,H,J": 3}
    assert set(sets(mine(illus, 2, partitioning="frontier"))) == {"A,N,P", "A,D,H,J", "D,H,J,N", "A,E,G,K,N"}


@pytest.mark.parametrize("kw", [{"group_rows": 20}, {"partitioning": "none"}, {"partitioning": "frontier"}, {"engine": "clausal"}, {"engine": "propagation"}, {"engine": "levelwise"}, {"engine": "clausal", "search": "length"}])
def test_partitionings_agree(spark, sf, kw):
    db = D.item_db(spark, sf, "order_mix")
    want = sets(mine(db, 0.2))
    assert len(want) == 59 and sets(mine(db, 0.2, **kw)) == want


def test_wide_masks(spark):
    tx = generate(spark, 70, 200, 0.2, 0.5, 1)
    db = build_item_db(tx)
    assert db.n == 70 and bits.is_wide(db.n)
    deep, whole = sets(mine(db, 0.2, group_rows=40)), sets(mine(db, 0.2, partitioning="none"))
    assert deep == whole and whole
    assert sets(mine(db, 0.2, partitioning="frontier")) == whole
    level = sets(mine(db, 0.2, engine="levelwise", output="frequent"))
    assert sets(mine(db, 0.2, output="frequent")) == level and set(whole) <= set(level)
    assert sets(mine(db, 0.2, engine="propagation", output="frequent")) == level
    p = profile(db).first()
    assert abs(p.density - 0.2) < 0.02
    closed = sets(mine(db, 0.2, output="closed"))
    assert closed == {k: v for k, v in level.items() if not any(v == w and set(k.split(",")) < set(x.split(",")) for x, w in level.items())}


def minimal_infrequent(db, minsup):
    """By plain enumeration of candidates one item larger than frequent sets."""
    rows, weights = db.rows()
    sup = lambda x: sum(w for r, w in zip(rows, weights) if r & x == x)
    level, out = [0], set()
    while level:
        nxt = set()
        for x in level:
            for i in range(x.bit_length(), db.n):
                y = x | 1 << i
                if sup(y) >= minsup:
                    nxt.add(y)
                elif all(y == 1 << j or sup(y & ~(1 << j)) >= minsup for j in range(db.n) if y >> j & 1):
                    out.add(y)
        level = nxt
    return {",".join(db.names[j] for j in range(db.n) if y >> j & 1) for y in out}


@pytest.mark.parametrize("kw", [{}, {"group_rows": 10}, {"group_rows": 2}, {"partitioning": "none"}, {"blocking": "supersets_explicit", "group_rows": 10}])
def test_dual_in_prefix_groups(spark, illus, kw):
    for db, minsup in ((illus, 2), (illus, 1), (build_item_db(generate(spark, 9, 60, 0.4, 0.4, 3)), 9)):
        got = {r.itemset for r in mine(db, minsup, output="infrequent", **kw).patterns.collect()}
        assert got == minimal_infrequent(db, minsup)
    wide = build_item_db(generate(spark, 66, 40, 0.12, 0.5, 2))
    assert {r.itemset for r in mine(wide, 8, output="infrequent", **({} if "blocking" in kw else kw)).patterns.collect()} == minimal_infrequent(wide, 8)
    assert sets(mine(wide, 8, formulation="dual", output="frequent")) == sets(mine(wide, 8, output="frequent"))


def test_bounds_cut_the_search(spark, sf):
    db = D.item_db(spark, sf, "order_mix")
    every = sets(mine(db, 0.1, output="frequent"))
    items = lambda k: k.split(",")
    assert sets(mine(db, 0.1, output="frequent", max_size=2)) == {k: v for k, v in every.items() if len(items(k)) <= 2}
    assert sets(mine(db, 0.1, output="frequent", engine="levelwise", max_size=2)) == {k: v for k, v in every.items() if len(items(k)) <= 2}
    load = {"rf=N": 2.0, "ls=O": 1.5, "ls=F": 0.5}
    total = lambda k: sum(load.get(x, 0.0) for x in items(k))
    assert sets(mine(db, 0.1, output="frequent", weights=load, max_weight=2.0)) == {k: v for k, v in every.items() if total(k) <= 2}
    assert sets(mine(db, 0.1, output="frequent", weights=load, min_weight=2.0)) == {k: v for k, v in every.items() if total(k) >= 2}
    assert sets(mine(db, 0.1, output="frequent", must_not=["rf=N", "ls=O"])) == {k: v for k, v in every.items() if not {"rf=N", "ls=O"} & set(items(k))}
    assert sets(mine(db, 0.1, output="frequent", any_of=[["rf=A", "rf=R"], ["ls=F"]])) == {k: v for k, v in every.items() if {"rf=A", "rf=R"} & set(items(k)) and "ls=F" in items(k)}
    assert sets(mine(db, 0.1, output="frequent", must_contain=["rf=N"], max_size=3, weights=load, max_weight=3.5)) == {k: v for k, v in every.items() if "rf=N" in items(k) and len(items(k)) <= 3 and total(k) <= 3.5}
    from patternspark.plans.mine import top_k_longest

    border = sorted(((-len(items(k)), k) for k in sets(mine(db, 0.1))))
    assert [r.itemset for r in top_k_longest(db, 0.1, 3).collect()] == [k for _, k in border[:3]]
    with pytest.raises(OutOfBudget):
        mine(db, 1, engine="propagation", partitioning="none", seconds=1e-9, output="frequent").patterns


def test_matches_by_rarest_item(spark, sf, monkeypatch):
    db = D.item_db(spark, sf, "order_mix")
    want = sets(mine(db, 0.1, output="frequent"))
    monkeypatch.setattr(measure, "BROADCAST_CANDIDATES", 3)
    assert sets(mine(db, 0.1, output="frequent")) == want
    assert sets(mine(db, 0.1, engine="levelwise", output="frequent")) == want
    cand = measure.candidates(db, [0, 1, 3])
    assert measure.support(db, cand).where("mask = 0").first().sup == sum(db.rows()[1])


def test_long_border_sets_are_expanded(spark):
    db = build_item_db(spark.createDataFrame([(1, [f"i{k:02d}" for k in range(12)]), (2, ["i00", "i05"])], "tid long, items array<string>"))
    assert mine(db, 1, output="frequent").masks.count() == 2**12 - 1


def test_encodings(spark, illus):
    tx = D.illus(spark)
    names = list(D.ALPHABET)
    size = encode.formula_size(encode.core(tx, names, 3)).first()
    assert (size.variables, size.binary, size.long - 1, size.pb) == (22, 64, 6, 16)
    size = encode.formula_size(encode.core(tx, names, 3, kind="reduced")).first()
    assert (size.binary, size.long - 1, size.pb) == (0, 6, 22)
    assert encode.opb_lines(encode.core(tx, names, 3)).count() == 64 + 6 + 16 + 1
    assert encode.cnf_lines(encode.numbered(encode.coverage(tx, names))).count() == 70
    weighted = encode.weighted_frequency(illus.masks, illus.names, 3)
    assert weighted.count() == 13


def truth(formula, items, rows):
    """All (itemset, rows) pairs of a formula relation, by enumeration."""
    names = [f"I_{i}" for i in items] + [f"T_{t}" for t in rows]
    out = set()
    for code in range(1 << len(names)):
        val = {v: code >> k & 1 for k, v in enumerate(names)}
        ok = True
        for c in formula:
            terms = [(x["coef"], val[x["var"]] ^ x["neg"]) for x in c["lits"]]
            total = sum(k * v for k, v in terms)
            ok &= any(v for _, v in terms) if c["op"] == "or" else total >= c["bound"] if c["op"] == ">=" else total <= c["bound"] if c["op"] == "<=" else total == c["bound"]
        if ok:
            out.add(code)
    return out


def test_encodings_have_the_same_models(spark):
    tx = spark.createDataFrame([(1, ["a", "b"]), (2, ["a"]), (3, ["b", "c"])], "tid long, items array<string>")
    names, rows = ["a", "b", "c"], [1, 2, 3]
    got = [truth([r.asDict(recursive=True) for r in encode.core(tx, names, 2, kind=k, freq=f).collect()], names, rows) for k, f in (("clausal", "reified"), ("reduced", "reified"), ("positive", "reified"), ("clausal", "plain"))]
    assert got[0] == got[1] == got[2] == got[3] and len(got[0]) == 2  # {a}, {b}
    low = truth([r.asDict(recursive=True) for r in encode.dual(tx, names, 2).collect()], names, rows)
    assert len(low) == 7 - 2
    top = encode.core(tx, names, 2).select("family", "op", "bound", "lits").union(encode.maximality(tx, names, 2, 3))
    assert len(truth([r.asDict(recursive=True) for r in top.collect()], names, rows)) == 2


def test_constraints_and_model(spark, sf):
    db = D.item_db(spark, sf, "order_mix")
    fr = sets(mine(db, 0.2, output="frequent"))
    must = sets(Model(db).require(Coverage("reduced"), Frequency(0.2), MustContain("rf=N")).solve(output="frequent"))
    assert must == {k: v for k, v in fr.items() if "rf=N" in k.split(",")}
    assert is_satisfiable(db, 0.2) and not is_satisfiable(db, db.m + 1)
    r = mine(db, 0.2, output="frequent")
    assert sets(r.refine(F.col("size") <= 2)) == {k: v for k, v in fr.items() if len(k.split(",")) <= 2}
    assert sets(r.refine(theta=0.4)) == {k: v for k, v in fr.items() if v >= db.minsup(0.4)}
    assert len(sets(r.refine(theta=0.3, output="maximal"))) > 0


def test_set_algebra_matches_its_cnf():
    import itertools

    n = 2
    for kind, fn in (("equal", lambda p, q, r: p == q), ("difference", lambda p, q, r: p & ~q == r), ("intersection", lambda p, q, r: p & q == r), ("union", lambda p, q, r: p | q == r)):
        cnf = constraints.set_cnf(kind, n)
        for p, q, r in itertools.product(range(1 << n), repeat=3):
            val = [(s >> i) & 1 for s in (p, q, r) for i in range(n)]
            assert all(any(val[abs(x) - 1] == (x > 0) for x in c) for c in cnf) == fn(p, q, r)


def test_expressions_to_cnf():
    import itertools

    e = ("iff", 1, ("or", 2, ("and", -3, ("implies", 2, 3))))
    cnf = constraints.to_cnf(e)

    def ev(x, a):
        if isinstance(x, int):
            return a[abs(x) - 1] == (x > 0)
        op, *args = x
        v = [ev(y, a) for y in args]
        return {"and": all(v), "or": any(v), "not": not v[0], "implies": not v[0] or v[-1], "iff": v[0] == v[-1]}[op]

    for a in itertools.product([False, True], repeat=3):
        assert ev(e, a) == all(any(a[abs(x) - 1] == (x > 0) for x in c) for c in cnf)


def test_freqsat(spark):
    cons = [freqsat.constraint(*c) for c in freqsat.WORKED]
    assert all(r.ok for r in freqsat.freqsat_check(spark, freqsat.WITNESS, cons).collect())
    status, rows = freqsat.freqsat(cons, min_rows=8, max_rows=8)
    assert status == "yes" and all(r.ok for r in freqsat.freqsat_check(spark, rows, cons).collect())
    assert freqsat.freqsat([freqsat.constraint("a", 1, 1), freqsat.constraint("b", 1, 1), freqsat.constraint("ab", 0, 0)])[0] == "no"


def test_frequencies_are_decided_exactly(spark):
    import random
    from fractions import Fraction

    r = random.Random(5)
    for _ in range(25):  # frequencies of a real database can be kept, and by the shares that are found
        rows = ["".join(i for i in "abcd" if r.random() < 0.5) for _ in range(r.randint(1, 7))]
        cons = [freqsat.constraint(own, f, f) for own in {"".join(sorted(r.sample("abcd", r.randint(1, 3)))) for _ in range(4)} for f in [Fraction(sum(set(own) <= set(x) for x in rows), len(rows))]]
        got = freqsat.shares(cons)
        assert got is not None and sum(got.values()) == 1 and min(got.values()) > 0
        assert all(sum(v for x, v in got.items() if set(own) <= set(x)) == lo for own, lo, _ in cons)
    half = Fraction(1, 2)
    apart = [*[freqsat.constraint(x, half, 1) for x in "abc"], *[freqsat.constraint(x, 0, 0) for x in ("ab", "ac", "bc")]]
    assert freqsat.freqsat(apart) == ("no", []) and not freqsat.contradicts(apart)
    third = Fraction(1, 31)  # a witness needs 31 rows: more than the solver is asked to try
    status, rows = freqsat.freqsat([freqsat.constraint("a", third, third)], max_rows=3)
    assert status == "yes" and Fraction(sum("a" in x for x in rows), len(rows)) == third


def test_bounds_hold(spark, sf):
    db = D.item_db(spark, sf, "order_mix")
    fr = mine(db, 0.2, output="frequent").masks.where(F.bit_count("mask") <= 3)
    got = condense.deduce_bounds(fr, db.n, db.m).collect()
    assert got and all(r.lower <= r.sup <= r.upper for r in got)


def test_edges(spark):
    empty = build_item_db(spark.createDataFrame([], "tid long, items array<string>"))
    assert mine(empty, 0.5).masks.count() == 0
    db = build_item_db(spark.createDataFrame([(1, ["a", "b"]), (2, ["a", "b"]), (3, []), (4, ["a", None])], "tid long, items array<string>"))
    assert db.m == 4 and sets(mine(db, 2)) == {"a,b": 2}
    assert mine(db, 5).masks.count() == 0
    assert absolute(0.2, 14743) == 2949 and absolute(0.5, 6) == 3
    with pytest.raises(ValueError):
        absolute(0, 5)


def test_bins_and_advice(spark):
    b = Bins((1.0, 2.0), ("lo", "mid", "hi"))
    rows = spark.createDataFrame([(0.5,), (1.0,), (3.0,), (None,)], "x double").select(b.label(F.col("x")).alias("l")).collect()
    assert [r.l for r in rows] == ["lo", "mid", "hi", None]
    assert recommend(0.5, 0.1).method == "growing" and recommend(0.2, 0.1).method == "dual" and recommend(0.2, 0.5).method == "baseline"
    assert choose_formulation(0.2, 0.01, 0.1) == "dual" and choose_formulation(0.2, 3.0, 0.1) == "primal" and recommend(0.2, 0.1, item_ratio=3.0).method == "baseline"
    q = Bins.quantile(spark.range(100), "id", ["a", "b", "c", "d"])
    assert len(q.edges) == 3


def test_stream_windows_are_mined_once(spark, tmp_path):
    from patternspark.streaming import windows

    rows = [(i, f"2024-01-0{1 + i // 8} 0{i % 8}:00:00", i % 3, "abc"[i % 3 if i % 5 else 0]) for i in range(24)]
    src = str(tmp_path / "in")
    spark.createDataFrame(rows, "event_id long, t string, user_id long, event_type string").selectExpr("event_id", "cast(t as timestamp_ntz) ts", "user_id", "event_type", "1.0D value", "'{}' props").coalesce(1).write.parquet(src)
    got = []
    windows.stream_itemsets(windows.events(spark, src), 1, lambda df, n: got.extend(df.collect()), checkpoint=str(tmp_path / "cp")).awaitTermination()
    days = {r.start.day for r in got}
    assert days == {1, 2}  # the last day stays open
    whole = windows.window_baskets(windows.events(spark, src, stream=False)).where("day(start) = 1")
    want = sets(mine(build_item_db(whole.select(F.col("user").alias("tid"), "items")), 1, output="frequent"))
    assert {r.itemset: r.sup for r in got if r.start.day == 1} == want


def test_plans_stay_native_until_the_kernel(spark, sf):
    db = D.item_db(spark, sf, "line_attr")
    plan = db.masks._jdf.queryExecution().toString()
    assert "Python" not in plan and "Pandas" not in plan
    assert "l_comment" not in plan.split("Physical Plan")[1]


def test_frontier_rounds_end_with_the_whole_border_or_none(illus):
    want = {illus.mask(x.split(",")) for x in ("A,N,P", "A,D,H,J", "D,H,J,N", "A,E,G,K,N")}
    assert {r.mask for r in mine_growing_frontier(illus, 2)[0].collect()} == want
    with pytest.raises(OutOfBudget):
        mine_growing_frontier(illus, 2, max_rounds=1)


@pytest.mark.parametrize("method", ["seqcounter", "bdd", "totalizer", "network"])
def test_cardinality_clauses_count_rows(spark, method):
    """An item that is chosen is satisfiable just with at least ``minsup`` of its rows, for every choice of rows."""
    from patternspark.operators.solver import ClauseSolver

    tx = spark.createDataFrame([(t, ["a"] + (["b"] if t < 4 else []) + (["c"] if t == 1 else [])) for t in range(1, 7)], "tid long, items array<string>")
    for minsup in (1, 2, 3, 5):
        clauses = [[(x.var, x.neg) for x in r.lits] for r in encode.cardinality_cnf(tx, ["a", "b", "c"], minsup, method).collect()]
        names = sorted({v for c in clauses for v, _ in c} | {f"T_{t}" for t in range(1, 7)})
        for code in range(64):
            for item, own in (("I_a", range(1, 7)), ("I_b", range(1, 4)), ("I_c", [1])):
                s = ClauseSolver()
                var = {v: s.new_var() for v in names}
                for c in clauses:
                    s.add_clause([-var[v] if neg else var[v] for v, neg in c])
                want = sum(code >> (t - 1) & 1 for t in own) >= minsup
                fixed = [var[f"T_{t}"] if code >> (t - 1) & 1 else -var[f"T_{t}"] for t in range(1, 7)]
                assert (s.ok and s.solve([*([var[item]] if item in var else []), *fixed])) == want, (method, minsup, code, item)


def test_merge_networks_sort():
    import itertools

    for p in (1, 2, 4, 8):
        for bits_ in itertools.product((0, 1), repeat=p):
            x = list(bits_)
            for _, a, b in encode.merge_network(p):
                x[a], x[b] = max(x[a], x[b]), min(x[a], x[b])
            assert x == sorted(bits_, reverse=True)


def test_pattern_sets(spark):
    db = build_item_db(spark.createDataFrame([(1, ["a", "x"]), (2, ["a", "x", "y"]), (3, ["b", "y"]), (4, ["b", "y"]), (5, ["b", "x", "z"])], "tid long, items array<string>"))
    fr = mine(db, 1, output="frequent").masks
    name = lambda ms: tuple(",".join(db.names[i] for i in bits.bits(m)) for m in ms)
    parts = {name(r.masks) for r in constraints.conceptual_clustering(db, fr, 2).collect()}
    assert ("a", "b") in parts and all(len(x) == 2 for x in parts) and ("a", "x") not in parts
    good = {name(r.masks): r.covered for r in constraints.concept_learning(db, fr, 2, db.names.index("b")).collect()}
    assert good[("z", "x,z")] == 1 and ("a", "y") not in good and all("x" not in k for k in good)
    same = {(name([r.p])[0], name([r.q])[0]): r.jaccard for r in constraints.redescriptions(db, fr, db.mask("a,b"), 0.6).collect()}
    assert same[("a", "x")] == pytest.approx(2 / 3, abs=1e-6) and ("b", "x") not in same
    with pytest.raises(ValueError):
        measure.bounded(spark.range(5), 4, "rows")


def test_costs(spark, sf):
    from patternspark.operators import trace

    db = D.item_db(spark, sf, "user_day")
    got = trace.conflicts(mine(db, 0.1, engine="clausal", partitioning="none").trace).collect()
    assert got and all(r.decisions >= 0 and r.restarts >= 0 for r in got) and sum(r.decisions for r in got) > 0
    cost = trace.plan_cost(db.masks.groupBy("mask").count()).first()
    assert cost.shuffles == 1 and cost.python == 0 and cost.scans == 1
    run = trace.run_cost(spark, lambda: db.masks)
    assert run.first().jobs >= 1 and run.first().rows == db.masks.count()


def _content(db):
    return db.names, db.supports, db.m, sorted((bits.to_int(r.mask), r.w) for r in db.masks.collect()), db.masks.dtypes


def test_attributes_collapse_before_items_are_made(spark, sf):
    from patternspark.sources.itemize import ItemRule, itemize_attributes

    for name in D.ATTRIBUTES:
        assert _content(D.item_db(spark, sf, name)) == _content(build_item_db(D.transactions(spark, sf, name)))
    odd = spark.createDataFrame([(1, "x", 0.0), (2, "x", -0.0), (3, None, float("nan")), (4, "x", 0.0), (5, None, None)], "t long, a string, b double")
    rules = [ItemRule("b", "b"), ItemRule("a", "a", null_item=True)]
    same, each = (build_item_db(itemize_attributes(odd, "t", rules, collapse=c)) for c in (True, False))
    assert _content(same) == _content(each) and same.m == 5


def test_listed_items_give_the_gathered_database(spark, sf):
    for name in D.LISTED:
        for theta in (None, 0.2):
            assert _content(D.item_db(spark, sf, name, theta=theta)) == _content(build_item_db(D.transactions(spark, sf, name), theta=theta))
    tx = spark.createDataFrame([(1, "a"), (1, "a"), (1, None), (2, None), (None, "b"), (3, "b"), (3, "c")], "tid long, item string")
    wide = spark.createDataFrame([(i, f"i{i * j % 90:02d}") for i in range(40) for j in range(5)], "tid long, item string")
    for t in (tx, wide):
        more = t.select("item").union(spark.createDataFrame([("zz",), ("a0",), (None,)], "item string"))
        for theta in (None, 0.3, 2):
            assert _content(build_item_db(t, theta=theta, listed=more)) == _content(build_item_db(t, theta=theta))
    with pytest.raises(Exception, match="not listed"):
        build_item_db(tx, listed=spark.createDataFrame([("a",)], "item string"))


def test_databases_read_their_source_once(spark, sf, monkeypatch):
    from patternspark.operators import itemdb

    written = []
    monkeypatch.setattr(itemdb, "cut", lambda df, tag: written.append((tag, df._jdf.queryExecution().executedPlan().toString())) or cut(df, tag))
    D.item_db(spark, sf, "line_attr")
    (_, source), (_, masks) = written
    assert "lineitem" in source and "lineitem" not in masks
    written.clear()
    D.item_db(spark, sf, "order_mix")
    assert [tag for tag, _ in written] == ["masks"] and "collect_set" not in written[0][1]
