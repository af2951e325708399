"""Every method of the engine as a query over the given tables, with its SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable
from fractions import Fraction
from functools import partial

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bits
from ..operators import blocking as B
from ..operators import condense, constraints, encode, freqsat, measure, trace
from ..operators.baseline import mine_fpgrowth
from ..operators.bitset import ReifiedSum, SumBound
from ..operators.frontier import local_length_counts
from ..operators.itemdb import binary_matrix, build_item_db, profile
from ..operators.solver import PROFILES, Polarity
from ..operators.vote import mine_local_vote
from ..session import cut
from ..sources import databases as D
from ..sources.generator import generate, generate_sql
from ..streaming import windows
from . import oracles as O
from . import workloads
from .advisor import advise, mine_auto
from .mine import AnyOf, Coverage, Frequency, MaxSize, Model, MustContain, MustNotContain, mine, top_k_longest

Query = Callable[[SparkSession, str], DataFrame]


def _label(theta: float | int) -> str:
    return f"t{theta}" if isinstance(theta, int) else str(theta).replace(".", "_")


def mined(spark: SparkSession, sf_dir: str, db: str, theta: float | int, **settings) -> DataFrame:
    return mine(D.item_db(spark, sf_dir, db), theta, **settings).patterns


def _minimal_infrequent(spark: SparkSession, sf_dir: str, db: str, theta: float, **settings) -> DataFrame:
    return mine(D.item_db(spark, sf_dir, db), theta, output="infrequent", **settings).patterns.select("itemset", "size")


def _itemize(spark: SparkSession, sf_dir: str, db: str) -> DataFrame:
    tx = D.transactions(spark, sf_dir, db)
    long = tx.select("tid", F.explode("items").alias("item")) if "items" in tx.columns else tx.select("tid", "item").distinct()
    return long.groupBy("item").agg(F.count(F.lit(1)).alias("n")) if db == "line_attr" else long


def _profile(spark: SparkSession, sf_dir: str, db: str) -> DataFrame:
    return profile(D.item_db(spark, sf_dir, db))


def _collapse(spark: SparkSession, sf_dir: str, db: str) -> DataFrame:
    d = D.item_db(spark, sf_dir, db)
    return d.masks.select(bits.names_of(F.col("mask"), d.names).alias("itemset"), F.col("w").cast("long").alias("w"))


def _matrix(spark: SparkSession, sf_dir: str, db: str) -> DataFrame:
    tx = D.transactions(spark, sf_dir, db).groupBy("tid").agg(F.array_sort(F.collect_set("item")).alias("items"))
    return binary_matrix(tx, [r[0] for r in tx.select(F.explode("items")).distinct().collect()])


def _items_of(tx: DataFrame) -> list[str]:
    return sorted(r[0] for r in tx.select(F.explode("items")).distinct().collect())


_ASKED = ["J,N", "E,N", "D,H,J", "A,N", "F"]


#: Item sets asked of the customers.
_ASKED_CUST = ["bal=a,seg=BUILDING", "nat=0,seg=BUILDING", "bal=d,nat=1,seg=MACHINERY", "bal=b,nat=3", "nat=2"]


def _coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measure.coverage(D.cust_attr(spark, sf_dir), _ASKED_CUST)


def _support(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = D.item_db(spark, sf_dir, "illus")
    return measure.patterns(measure.support(d, measure.candidates(d, _ASKED)), d)


def _pairs(spark: SparkSession, sf_dir: str, db: str, theta: float):
    tx = D.transactions(spark, sf_dir, db).groupBy("tid").agg(F.array_sort(F.collect_set("item")).alias("items"))
    d = build_item_db(tx)
    sets = [r.itemset for r in mine(d, theta, output="frequent").patterns.collect()]
    return tx, measure.itemset_transaction_pairs(tx, sets), d.minsup(theta)


def _check(spark: SparkSession, sf_dir: str, kind: str, db: str = "user_day", theta: float = 0.2) -> DataFrame:
    tx, pairs, minsup = _pairs(spark, sf_dir, db, theta)
    if kind == "coverage":
        return measure.check_coverage(tx, pairs)
    if kind == "frequency":
        return measure.check_frequency(pairs, minsup)
    return measure.check_reified_frequency(tx, pairs, minsup)


def _border(spark: SparkSession, sf_dir: str, db: str, theta: float) -> DataFrame:
    d = D.item_db(spark, sf_dir, db)
    return condense.border_profile(mine(d, theta, output="frequent").masks, d)


def _transactions_of(spark: SparkSession, sf_dir: str, db: str) -> DataFrame:
    tx = D.transactions(spark, sf_dir, db)
    return tx if "items" in tx.columns else tx.groupBy("tid").agg(F.array_sort(F.collect_set("item")).alias("items"))


def encoding(spark: SparkSession, sf_dir: str, db: str, theta: float | int, kind: str) -> DataFrame:
    """The formula relation of a database under an encoding."""
    tx = _transactions_of(spark, sf_dir, db)
    names = list(D.ALPHABET) if db == "illus_all" else sorted(r[0] for r in tx.select(F.explode("items")).distinct().collect())
    from ..operators.itemdb import absolute

    minsup = absolute(theta, tx.count())
    if kind in ("clausal", "reduced", "positive"):
        return encode.core(tx, names, minsup, kind=kind)
    if kind == "plain":
        return encode.core(tx, names, minsup, freq="plain")
    if kind == "dual":
        return encode.dual(tx, names, minsup)
    core = encode.core(tx, names, minsup)
    if kind == "incremental":
        return encode.restrict_incremental(core, names)
    if kind == "fixed":
        return encode.restrict_fixed(core, names)
    if kind == "length":
        return encode.length(names, core)
    if kind == "size":
        return encode.length(names, core, 3)
    return encode.numbered(core.select("family", "op", "bound", "lits").union(encode.maximality(tx, names, minsup, tx.count())))


def _encoding_size(spark: SparkSession, sf_dir: str, db: str, theta: float | int, kind: str) -> DataFrame:
    return encode.formula_size(encoding(spark, sf_dir, db, theta, kind))


def _coverage_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    tx = D.cust_attr(spark, sf_dir)
    f = encode.coverage(tx, _items_of(tx)).where("family = 'coverage_binary'")
    return f.select(F.substring(F.element_at("lits", 1)["var"], 3, 99).cast("long").alias("tid"), F.substring(F.element_at("lits", 2)["var"], 3, 99).alias("item"))


def _frequency_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    tx = D.cust_attr(spark, sf_dir)
    f = encode.frequency(tx, _items_of(tx), 3).select(F.explode("lits").alias("x"), F.element_at("lits", 1)["var"].alias("v"), "bound")
    return f.where("x.var like 'T%'").select(F.substring("v", 3, 99).alias("item"), F.substring("x.var", 3, 99).cast("long").alias("tid"), "bound")


def _user_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``tid, items``: the days of each user, the user being the only item: many items of some dozens of rows."""
    days = D.user_day(spark, sf_dir).select("tid").distinct()
    return days.select("tid", F.array(F.floor(F.col("tid") / 1000).cast("string")).alias("items"))


def _cardinality(spark: SparkSession, sf_dir: str, method: str) -> DataFrame:
    return encode.formula_size(encode.cardinality_cnf(_user_days(spark, sf_dir), [], 3, method))


def _opb(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode.opb_lines(encode.core(D.illus(spark), list(D.ALPHABET), 3)).select("value")


def _cnf(spark: SparkSession, sf_dir: str) -> DataFrame:
    tx = D.cust_attr(spark, sf_dir)
    return encode.cnf_lines(encode.numbered(encode.coverage(tx, _items_of(tx)))).select("value")


def _search_counts(spark: SparkSession, sf_dir: str, db: str, theta: float) -> DataFrame:
    d = D.item_db(spark, sf_dir, db)
    out = None
    for search, kinds in (("growing", ["alpha"]), ("longest", ["lsm"]), ("length", ["ld_sat", "ld_unsat"])):
        got = trace.search_counts(mine(d, theta, engine="clausal", search=search, partitioning="none").trace).where(F.col("kind").isin(kinds))
        out = got if out is None else out.union(got)
    return out


def _trace(spark: SparkSession, sf_dir: str, fn, db: str = "order_mix", theta: float = 0.2, **settings) -> DataFrame:
    return fn(mine(D.item_db(spark, sf_dir, db), theta, **({"engine": "clausal", "partitioning": "none"} | settings)).trace)


def _overhead(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = D.item_db(spark, sf_dir, "order_mix")
    one = lambda r: mine(d, 0.2, engine="clausal", partitioning="none", restriction=r).trace
    return trace.overhead(one("incremental"), one("free"))


def _blocked(spark: SparkSession, sf_dir: str, db: str) -> DataFrame:
    """``option, itemset, clauses, blocked`` of each distinct basket: how many clauses an option writes, and how many
    itemsets they exclude, all of them tried (few items only)."""
    d = D.item_db(spark, sf_dir, db)
    n = d.n

    def run(batches):
        for b in batches:
            rows = []
            for mask in b["mask"].tolist():
                for o in (B.ITEMS, B.SUBSETS, B.SUBSET, B.SUPERSETS, B.SUPERSET):
                    cs = B.blocking_clauses(mask, n, o)
                    rows.append((o, mask, len(cs), sum(any(B.violates(x, c) for c in cs) for x in range(1, 1 << n))))
            yield pd.DataFrame(rows, columns=["option", "mask", "clauses", "blocked"])

    got = d.masks.select("mask").mapInPandas(run, "option string, mask long, clauses long, blocked long")
    return got.select("option", bits.names_of(F.col("mask"), d.names).alias("itemset"), "clauses", "blocked")


def _sizes(df: DataFrame) -> DataFrame:
    return df.groupBy("size").agg(F.count(F.lit(1)).alias("n"))


def _top_sizes(spark: SparkSession, sf_dir: str, db: str, theta: float, k: int, **settings) -> DataFrame:
    return _sizes(top_k_longest(D.item_db(spark, sf_dir, db), theta, k, **settings))


def _with(spark: SparkSession, sf_dir: str, db: str, theta: float, fn) -> DataFrame:
    d = D.item_db(spark, sf_dir, db)
    return fn(d, mine(d, theta, output="frequent").masks)


def _rules(d, f):
    return constraints.association_rules(f, d, 0.6)


def _area(d, f):
    return constraints.with_area(f, d).where("size >= 2").orderBy(F.col("area").desc(), "itemset").limit(20)


def _discriminative(d, f):
    return constraints.discriminative(d, f, d.names.index("q=1"))


def _overlap(d, f):
    got = constraints.overlap_pairs(d, f.where(F.bit_count("mask") == 2))
    return got.select(bits.names_of(F.col("p"), d.names).alias("p"), bits.names_of(F.col("q"), d.names).alias("q"), "overlap", "coverage2")


def _cover_items(d, f):
    return constraints.cover_items(d, condense.maximal(f, d.n).select("mask"))


def _cover_rows(d, f):
    return constraints.cover_transactions(d, condense.maximal(f, d.n).select("mask"))


def _tiling(d, f):
    got = constraints.k_pattern_set(d, f, 2, max_overlap_items=0)
    return got.select(bits.names_of(F.element_at("masks", 1), d.names).alias("a"), bits.names_of(F.element_at("masks", 2), d.names).alias("b"), "area")


def _tiling3(d, f):
    got = constraints.k_pattern_set(d, f, 3, max_overlap_items=0)
    return got.agg(F.count(F.lit(1)).alias("sets"), F.max("area").alias("best"))


def _bounds(d, f):
    got = condense.deduce_bounds(f.where(F.bit_count("mask") <= 3), d.n, d.m).where(F.bit_count("mask") == 3)
    return got.select(bits.names_of(F.col("mask"), d.names).alias("itemset"), "lower", "upper", F.col("sup").cast("long").alias("sup"))


def _must(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mined(spark, sf_dir, "order_mix", 0.1, must_contain=["rf=N"], output="frequent", max_size=4)


def _reducts(spark: SparkSession, sf_dir: str) -> DataFrame:
    part = D.table(spark, sf_dir, "part").select("p_type", F.floor((F.col("p_size") - 1) / 10).alias("size"), (F.col("p_retailprice") < 950).alias("cheap"), F.col("p_brand").substr(1, 7).alias("maker"))
    return constraints.minimal_reducts(part, ["p_type", "size", "cheap"], "maker")


def _freqsat_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    return freqsat.freqsat_check(spark, freqsat.WITNESS, [freqsat.constraint(*c) for c in freqsat.WORKED])


def _freqsat(spark: SparkSession, sf_dir: str) -> DataFrame:
    status, rows = freqsat.freqsat([freqsat.constraint(*c) for c in freqsat.WORKED])
    bad, _ = freqsat.freqsat([freqsat.constraint("a", 1, 1), freqsat.constraint("b", 1, 1), freqsat.constraint("ab", 0, 0)])
    return spark.createDataFrame([("worked", status, len(rows)), ("contradiction", bad, 0)], "instance string, status string, rows int")


def _freqsat_decided(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Instances with a known answer: the worked one, pairs that exclude each other, a cycle of rules, three disjoint halves."""
    c, one, half = freqsat.constraint, Fraction(1), Fraction(1, 2)
    cases = [
        ("worked", [c(*x) for x in freqsat.WORKED], ()),
        ("three_disjoint_halves", [*[c(x, half, 1) for x in "abc"], *[c(x, 0, 0) for x in ("ab", "ac", "bc")]], ()),
        ("two_disjoint_halves", [*[c(x, half, half) for x in "ab"], c("ab", 0, 0)], ()),
        ("rule_kept", [c("a", half, 1), c("b", half, half)], [(("a",), ("b",), Fraction(3, 4), one)]),
        ("rule_broken", [c("a", Fraction(4, 5), 1), c("b", 0, half)], [(("a",), ("b",), Fraction(3, 4), one)]),
    ]
    rows = [(name, status, all(lo <= Fraction(sum(set(own) <= set(r) for r in got), len(got)) <= hi for own, lo, hi in cons) if got else None) for name, cons, rules in cases for status, got in [freqsat.freqsat(cons, rules=rules)]]
    return spark.createDataFrame(rows, "instance string, status string, witness_ok boolean")


def _vote(spark: SparkSession, sf_dir: str, db: str, theta: float) -> DataFrame:
    d = D.item_db(spark, sf_dir, db)
    return measure.patterns(mine_local_vote(d, theta).select("mask", "sup"), d)


def _stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as a file stream, run until all is read; daily counts of each type from the memory sink."""
    import uuid

    name = f"days_{uuid.uuid4().hex}"
    ev = windows.events(spark, f"{sf_dir}/events.parquet*")
    q = windows.window_item_counts(ev).writeStream.format("memory").queryName(name).outputMode("complete").trigger(availableNow=True)
    from ..session import shared_dir

    q.option("checkpointLocation", f"{shared_dir(spark)}/stream-{name}").start().awaitTermination()
    return spark.table(name).select(F.date_format("start", "yyyy-MM-dd").alias("day"), F.col("item").alias("event_type"), "n")


def _generated(spark: SparkSession, sf_dir: str) -> DataFrame:
    return generate(spark, 20, 500, 0.3, 0.4, 7).select("tid", F.explode("items").alias("item"))


def _wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Maximal sets over 70 items: masks of two words."""
    return mine(build_item_db(generate(spark, 70, 200, 0.2, 0.5, 1)), 0.2, group_rows=60).patterns


def _advice(spark: SparkSession, sf_dir: str, db: str) -> DataFrame:
    return advise(D.item_db(spark, sf_dir, db), [0.01, 0.04, 0.05, 0.1, 0.2, 0.25, 0.3, 0.6])


def _cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supports of all attribute-value sets with at most one value an attribute, by the built-in cube."""
    tx = D.transactions(spark, sf_dir, "line_attr")
    attrs = ["rf", "ls", "qty", "disc", "tax"]
    got = tx.select(*[F.element_at(F.filter("items", _starts(a)), 1).alias(a) for a in attrs]).cube(*attrs).agg(F.count(F.lit(1)).alias("sup"))
    return got.select(F.array_join(F.array_sort(F.array_compact(F.array(*attrs))), ",").alias("itemset"), "sup").where("itemset <> '' and sup >= 3000")


def _starts(a: str):
    return lambda x: x.startswith(a + "=")


def _lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return local_length_counts(D.item_db(spark, sf_dir, "order_mix")).withColumn("rows", F.col("rows").cast("long"))


def _fpgrowth(spark: SparkSession, sf_dir: str, db: str, theta: float) -> DataFrame:
    return mine_fpgrowth(_transactions_of(spark, sf_dir, db), theta)


def _auto(spark: SparkSession, sf_dir: str, db: str, theta: float) -> DataFrame:
    d = D.item_db(spark, sf_dir, db)
    return measure.patterns(condense.maximal(mine_auto(d, theta, output="frequent").masks, d.n), d)


def _rules_any(d, f):
    return constraints.association_rules(f, d, 0.5, max_head=None)


def _rules_low(d, f):
    return constraints.association_rules(f, d, 0.1, max_head=None)


def _clusters(d, f):
    got = constraints.conceptual_clustering(d, f, 2)
    return got.select(*[bits.names_of(F.element_at("masks", i), d.names).alias(c) for i, c in ((1, "a"), (2, "b"))], F.col("rows").cast("long").alias("rows"))


def _concepts(d, f):
    got = constraints.concept_learning(d, f.where(bits.size(F.col("mask"), d.n) <= 2), 2, d.names.index("pr=lo"), max_negative=0)
    return got.select(*[bits.names_of(F.element_at("masks", i), d.names).alias(c) for i, c in ((1, "a"), (2, "b"))], F.col("covered").cast("long").alias("covered"))


def _redescriptions(d, f):
    view = sum(1 << i for i, x in enumerate(d.names) if x.startswith("type="))
    got = constraints.redescriptions(d, f, view, 0.3)
    return got.select(bits.names_of(F.col("p"), d.names).alias("p"), bits.names_of(F.col("q"), d.names).alias("q"), "together", "jaccard")


def _bounded(spark: SparkSession, sf_dir: str, **kw) -> DataFrame:
    return mined(spark, sf_dir, "order_mix", 0.1, output="frequent", **kw)


def _exactness(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``method, missing, extra`` of each complete method against the level-wise one."""
    d = D.item_db(spark, sf_dir, "order_mix")
    want, out = cut(mine(d, 0.2, engine="levelwise", output="frequent").masks.select("mask", "sup"), "want"), None
    for name, kw in (("growing", {"engine": "clausal"}), ("length", {"engine": "clausal", "search": "length"}), ("dual", {"formulation": "dual"}), ("bitset", {}), ("propagation", {"engine": "propagation"}), ("frontier", {"partitioning": "frontier"})):
        got = measure.compare_sets(want, cut(mine(d, 0.2, output="frequent", **kw).masks.select("mask", "sup"), "got")).select(F.lit(name).alias("method"), "missing", "extra")
        out = got if out is None else out.union(got)
    return out


def _transition(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The threshold of the largest border of each database: a cost that is the same on every machine."""
    grid = workloads.w14_sweep(spark, sf_dir).where("config = 'bitset'")
    return trace.phase_transition(grid, "n_maximal").select("db", "theta", F.col("cost").cast("long").alias("n_maximal"))


def _transition_seconds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trace.phase_transition(workloads.w02_density(spark))


def _plan_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trace.plan_cost(mined(spark, sf_dir, "order_mix", 0.2, output="frequent"))


def _run_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trace.run_cost(spark, lambda: mined(spark, sf_dir, "order_mix", 0.2))


def _wide_sets(spark: SparkSession, sf_dir: str, n: int, **kw) -> DataFrame:
    return mine(build_item_db(generate(spark, n, 200, 0.2, 0.5, 1)), 0.15, output="frequent", max_size=3, **kw).patterns


def _wide_sql(n: int) -> str:
    """Frequent sets of up to three items by joins."""
    pair = "select a.item as x, b.item as y, a.tid from k a join k b on a.tid = b.tid and a.item < b.item"
    return O.base("", 0.15, generate_sql(n, 200, 0.2, 0.5, 1), 200) + f""", k as (select tid, item from tx join fi using (item)),
p2 as ({pair}), f2 as (select x, y, count(*)::bigint as sup from p2 group by all having count(*) >= (select minsup from ms)),
f3 as (select p2.x, p2.y, c.item as z, count(*)::bigint as sup from p2 join f2 on f2.x = p2.x and f2.y = p2.y join k c on c.tid = p2.tid and c.item > p2.y group by all having count(*) >= (select minsup from ms))
select item as itemset, 1::int as size, c::bigint as sup, round(c / 200.0, 6)::double as freq from fi
union all select x || ',' || y, 2, sup, round(sup / 200.0, 6)::double from f2 union all select x || ',' || y || ',' || z, 3, sup, round(sup / 200.0, 6)::double from f3"""


def _model(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = Model(D.item_db(spark, sf_dir, "order_mix")).require(Coverage("reduced"), Frequency(0.1), MustContain("ls=F"), MustNotContain("rf=A"), AnyOf(("rf=R,rf=N",)), MaxSize(4))
    return m.solve(output="frequent").patterns


def _refined(spark: SparkSession, sf_dir: str) -> DataFrame:
    first = mine(D.item_db(spark, sf_dir, "order_mix"), 0.1, output="frequent")
    return first.refine(F.col("size") >= 2, theta=0.2).patterns


def _weighted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per item the rows' weights of its weighted frequency constraint, largest and in sum."""
    d = D.item_db(spark, sf_dir, "user_day")
    f = encode.weighted_frequency(d.masks, d.names, d.minsup(0.1)).select(F.explode("lits").alias("x"), F.element_at("lits", 1)["var"].alias("v"))
    rows = f.where("not startswith(x.var, 'I_')").groupBy(F.substring("v", 3, 99).alias("item"))
    return rows.agg(F.count(F.lit(1)).alias("masks"), F.sum("x.coef").alias("total"), F.max("x.coef").alias("most"))


def _set_algebra(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The set constraints on all pairs of subsets of five items, and an itemset's member test."""
    n, one = 5, spark.range(32)
    t = one.select(F.col("id").alias("p")).crossJoin(F.broadcast(one.select(F.col("id").alias("q"))))
    p, q = F.col("p"), F.col("q")
    r = lambda fn: fn(p, q, n)
    return t.select(
        "p", "q", constraints.equal(p, q).alias("equal"), constraints.member(p, 3, n).alias("member"), r(bits.difference).alias("difference"), r(bits.intersection).alias("intersection"), r(bits.union).alias("union_"),
        constraints.union_is(p, q, F.lit(31).cast("long"), n).alias("all_items"), constraints.intersection_is(p, q, F.lit(0).cast("long"), n).alias("disjoint"), constraints.difference_is(p, q, F.lit(0).cast("long"), n).alias("inside"),
    )


def _selected(d, f):
    """Sets with a type, at most as many flags as types, not only types, and a bounded sum of prices."""
    x = constraints.Selected(d.names)
    typed, flag = (lambda i: i.startswith("type=")), (lambda i: i.startswith("rf="))
    price = {i: 2.0 if flag(i) else 0.5 for i in d.names}
    cond = x.any(typed) & (x.count(flag) <= x.count(typed)) & ~x.all(typed) & (x.sum(price) - x.count(flag) * 1.5 <= 1.5) & (x.minus(bits.literal(d.mask("ls=F"), d.n)).count() >= 2)
    return measure.patterns(f.where(cond), d)


#: An expression over three variables.
_EXPRESSION = ("iff", 1, ("or", 2, ("and", -3, ("implies", 2, 3))))


def _expression(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Truth table of an expression by its clauses."""
    cnf = constraints.to_cnf(_EXPRESSION)
    value = lambda x: (F.getbit("code", F.lit(abs(x) - 1)) == (1 if x > 0 else 0))
    holds = F.lit(True)
    for c in cnf:
        own = F.lit(False)
        for x in c:
            own = own | value(x)
        holds = holds & own
    return spark.range(8).select(F.col("id").alias("code")).select("code", holds.alias("holds"))


def _propagators(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bounds and decisions of the sum propagators on every partial assignment of four weights."""
    from itertools import product

    rows = []
    for code, state in enumerate(product((None, False, True), repeat=4)):
        s = SumBound([3, 2, 2, 1])
        for k, v in enumerate(state):
            if v is not None:
                s.fix(k, v)
        forced = ReifiedSum(s, 5).propagate()
        rows.append((code, s.lower, s.upper, s.at_least(5), forced is False))
    return spark.createDataFrame(rows, "code long, lower long, upper long, decided boolean, out boolean")


MIX, WORDS, EMB = "order_mix", "doc_words16", "emb_sign8"


def build() -> tuple[dict[str, Query], dict[str, str]]:
    q: dict[str, Query] = {}
    sql: dict[str, str] = {}

    def add(key: str, fn: Query, oracle: str | None = None) -> None:
        q[key] = fn
        if oracle:
            sql[key] = oracle

    for db in D.BUILDERS:
        if db != "illus":
            add(f"itemize_{db}", partial(_itemize, db=db), f"select item, count(*) as n from ({D.LONG_SQL[db]}) group by item" if db == "line_attr" else f"select tid::bigint as tid, item from ({D.LONG_SQL[db]})")
            add(f"profile_{db}", partial(_profile, db=db), O.profile_sql(db))
    add("binary_matrix_user_day", partial(_matrix, db="user_day"), O.base("user_day") + " select t.tid, fi.item, (tx.item is not null)::int as present from (select distinct tid from tx) t cross join fi left join tx on tx.tid = t.tid and tx.item = fi.item")
    add("collapse_line_attr", partial(_collapse, db="line_attr"), O.base("line_attr") + " select (select string_agg(item, ',' order by item) from fi where (mask >> id) & 1 = 1) as itemset, w from g")
    asked = ", ".join(f"('{','.join(sorted(x.split(',')))}')" for x in _ASKED)
    hits = f"asked(itemset) as (values {asked}), hit as (select itemset, t.tid from asked, (select distinct tid from tx) t where not exists (select 1 from (select unnest(string_split(itemset, ',')) as i) where i not in (select item from tx where tx.tid = t.tid)))"
    of_customers = ", ".join(f"('{','.join(sorted(x.split(',')))}')" for x in _ASKED_CUST)
    add("coverage_illus", _coverage, O.base("cust_attr") + f", asked(itemset) as (values {of_customers}) select itemset, tid::bigint as tid from asked join tx on list_contains(string_split(itemset, ','), item) group by itemset, tid having count(*) = len(string_split(itemset, ','))")
    add("support_illus", _support, O.base("illus") + ", " + hits + " select asked.itemset, length(replace(asked.itemset, ',', ''))::int as size, count(tid)::bigint as sup, round(count(tid) / 6.0, 6)::double as freq from asked left join hit using (itemset) group by all")
    for t in (1, 2, 3, 4):
        add(f"freq_illus_t{t}", partial(mined, db="illus", theta=t, output="frequent"), O.frequent_sql("illus", t))
        add(f"maximal_illus_t{t}", partial(mined, db="illus", theta=t), O.maximal_sql("illus", t))
    for kind, col in (("coverage", "covered"), ("frequency", "frequent"), ("reified", "frequent")):
        add(f"{kind}_check_user_day", partial(_check, kind=kind), O.frequent("user_day", 0.2) + f" select string_agg(item, ',' order by item) as itemset, true as {col} from ps join fi on (s >> id) & 1 = 1 group by s")

    for db, thetas in {MIX: (0.05, 0.2), "line_attr": (0.01, 0.05), "order_attr": (0.01, 0.05), "user_day": (0.01, 0.05), EMB: (0.01, 0.1), WORDS: (0.4,), "part_attr": (0.02,), "cust_attr": (0.02,), "label_attr": (0.1,)}.items():
        for t in thetas:
            k = f"{db}_{_label(t)}"
            add(f"freq_{k}", partial(mined, db=db, theta=t, output="frequent"), O.frequent_sql(db, t))
            add(f"maximal_{k}", partial(mined, db=db, theta=t), O.maximal_sql(db, t))
    add("maximal_order_brand_0_05", partial(mined, db="order_brand", theta=0.05), O.base("order_brand", 0.05) + """,
pr as (select a.item as x, b.item as y, count(*)::bigint as sup from (select tid, item from tx join fi using (item)) a join (select tid, item from tx join fi using (item)) b on a.tid = b.tid and a.item < b.item group by all having count(*) >= (select minsup from ms))
select x || ',' || y as itemset, 2::int as size, sup, round(sup / (select m from m)::double, 6) as freq from pr
union all select item, 1::int, c::bigint, round(c / (select m from m)::double, 6) from fi where item not in (select x from pr union all select y from pr)""")
    add("maximal_emb_sign16_0_4", partial(mined, db="emb_sign16", theta=0.4), O.base("emb_sign16", 0.4) + """,
pr as (select a.item as x, b.item as y, count(*)::bigint as sup from tx a join tx b on a.tid = b.tid and a.item < b.item group by all having count(*) >= (select minsup from ms))
select x || ',' || y as itemset, 2::int as size, sup, round(sup / (select m from m)::double, 6) as freq from pr
union all select item, 1::int, c::bigint, round(c / (select m from m)::double, 6) from fi where item not in (select x from pr union all select y from pr)""")

    t, k = 0.2, f"{MIX}_0_2"
    whole = {"engine": "clausal", "partitioning": "none"}
    mx, fr = O.maximal_sql(MIX, t), O.frequent_sql(MIX, t)
    for name, kw, oracle in (
        ("simple_items_only_order_mix_0_4", {"theta": 0.4, "search": "simple", "blocking": B.ITEMS, "output": "frequent"}, O.frequent_sql(MIX, 0.4)),
        ("simple_full_model_order_mix_0_4", {"theta": 0.4, "search": "simple", "blocking": B.FULL, "output": "frequent"}, O.frequent_sql(MIX, 0.4)),
        (f"simple_subsets_explicit_{k}", {"search": "simple", "blocking": B.SUBSETS}, mx),
        (f"simple_subset_compact_{k}", {"search": "simple", "blocking": B.SUBSET}, mx),
        (f"simple_adaptive_{k}", {"search": "simple", "blocking": "adaptive"}, mx),
        (f"simple_positive_polarity_{k}", {"search": "simple", "polarity": Polarity("pos")}, mx),
        (f"simple_negative_polarity_{k}", {"search": "simple", "polarity": Polarity("neg")}, mx),
        (f"dynamic_polarity_{k}", {"polarity": Polarity("dynamic")}, mx),
        (f"lsm_maximal_{k}", {"search": "longest"}, mx),
        (f"cmg_maximal_{k}", {}, mx),
        (f"cmg_incremental_{k}", {"restriction": "incremental"}, mx),
        (f"cmg_fixed_{MIX}_0_4", {"theta": 0.4, "restriction": "fixed"}, O.maximal_sql(MIX, 0.4)),
        (f"cmg_reduced_{k}", {"coverage": "reduced"}, mx),
        (f"cmg_positive_literals_{k}", {"coverage": "positive"}, mx),
        (f"cmg_plain_frequency_{k}", {"frequency": "plain"}, mx),
        (f"cmg_native_profile_{k}", {"profile": PROFILES["native"]}, mx),
        (f"cmg_jvm_profile_{k}", {"profile": PROFILES["jvm"]}, mx),
        ("cmg_blackbox_profile_order_mix_0_6", {"theta": 0.6, "profile": PROFILES["blackbox"]}, O.maximal_sql(MIX, 0.6)),
        (f"ld_maximal_{k}", {"search": "length"}, mx),
        (f"ld_bounded_{k}", {"search": "length", "bounds": "scan"}, mx),
        (f"ld_encoded_{k}", {"search": "length", "maximality": "encoded"}, mx),
        (f"dual_complement_{k}", {"formulation": "dual", "output": "frequent"}, fr),
        (f"cmg_partitioned_{k}", {"partitioning": "prefix"}, mx),
        (f"lsm_partitioned_{k}", {"partitioning": "prefix", "search": "longest"}, mx),
        (f"ld_partitioned_{k}", {"partitioning": "prefix", "search": "length"}, mx),
    ):
        add(name, partial(mined, db=MIX, **({"theta": t} | whole | kw)), oracle)
    for name, kw, oracle in (
        (f"bitset_deepened_{k}", {"group_rows": 100}, mx), (f"bitset_whole_{k}", {"partitioning": "none"}, mx), (f"cmg_frontier_{k}", {"partitioning": "frontier"}, mx),
        (f"cp_reified_{k}", {"engine": "propagation", "output": "frequent"}, fr), (f"cp_plain_{k}", {"engine": "propagation_plain", "output": "frequent"}, fr),
        (f"levelwise_{k}", {"engine": "levelwise", "output": "frequent"}, fr), (f"bruteforce_{k}", {"engine": "bruteforce", "output": "frequent"}, fr),
    ):
        add(name, partial(mined, db=MIX, theta=t, **kw), oracle)
    add(f"fpgrowth_{k}", partial(_fpgrowth, db=MIX, theta=t), O.frequent(MIX, t) + " select string_agg(item, ',' order by item) as itemset, bit_count(s)::int as size, any_value(sup) as sup from ps join fi on (s >> id) & 1 = 1 group by s")
    add(f"closed_{k}", partial(mined, db=MIX, theta=t, output="closed"), O.closed_sql(MIX, t))
    add("closed_doc_words16_0_3", partial(mined, db=WORDS, theta=0.3, output="closed"), O.closed_sql(WORDS, 0.3))
    add(f"dual_min_infrequent_{k}", partial(_minimal_infrequent, db=MIX, theta=t), O.infrequent_sql(MIX, t))
    add(f"dual_explicit_{MIX}_0_1", partial(_minimal_infrequent, db=MIX, theta=0.1, blocking=B.SUPERSETS), O.infrequent_sql(MIX, 0.1))
    for db, th in ((MIX, 0.2), (EMB, 0.2), (WORDS, 0.4), ("user_day", 0.1), ("label_attr", 0.1)):
        add(f"border_profile_{db}_{_label(th)}", partial(_border, db=db, theta=th), O.border_sql(db, th))
    add("search_counts_order_mix_0_4", partial(_search_counts, db=MIX, theta=0.4), O.frequent(MIX, 0.4) + " select kind, case kind when 'ld_unsat' then (select count(distinct item) from tx) else (select count(*) from mx) end as searches from (values ('alpha'), ('lsm'), ('ld_sat'), ('ld_unsat')) v(kind)")
    sizes = O.frequent(MIX, t) + " select bit_count(s)::int as size, count(*) as n from {} group by 1"
    add(f"lsm_sizes_{k}", lambda s, d: _sizes(mined(s, d, MIX, t, **whole, search="longest")), sizes.format("mx"))
    top = sizes.format("(select s from mx order by bit_count(s) desc limit 10)")
    add(f"topk_longest_sizes_{k}", partial(_top_sizes, db=MIX, theta=t, k=10), top)
    add(f"topk_lsm_sizes_{k}", partial(_top_sizes, db=MIX, theta=t, k=10, engine="clausal", partitioning="none"), top)

    for kind in ("clausal", "reduced", "positive", "plain", "dual", "incremental", "fixed", "length", "size", "maximality"):
        for db in ("illus", "user_day", "label_attr") if kind in ("clausal", "reduced", "positive") else ("user_day",):
            own = "cust_attr" if db == "illus" else db
            add(f"enc_size_{kind}_{db}", partial(_encoding_size, db=own, theta=3 if db == "illus" else 0.1, kind=kind), O.encoding_size_sql(own, kind))
    add("enc_coverage_rows_illus", _coverage_rows, O.base("cust_attr") + " select t.tid::bigint as tid, fi.item from (select distinct tid from tx) t cross join fi where not exists (select 1 from tx where tx.tid = t.tid and tx.item = fi.item)")
    add("enc_frequency_rows_illus", _frequency_rows, O.base("cust_attr") + " select item, tid::bigint as tid, 3::bigint as bound from tx")
    for method in ("seqcounter", "bdd", "totalizer", "network"):
        add(f"enc_cardinality_{method}_illus", partial(_cardinality, method=method))
    add("opb_illus", _opb)
    add("cnf_illus", _cnf)
    add("blocking_counts", partial(_blocked, db="user_day"), O.base("user_day") + """, o as (select (select string_agg(item, ',' order by item) from fi where (mask >> id) & 1 = 1) as itemset, bit_count(mask) as k, (select count(*) from fi) as n from g)
select 'items_only' as option, itemset, 1::bigint as clauses, 1::bigint as blocked from o
union all select 'subsets_explicit', itemset, (2 ** k - 1)::bigint, (2 ** k - 1)::bigint from o
union all select 'subset_compact', itemset, 1, (2 ** k - 1)::bigint from o
union all select 'supersets_explicit', itemset, (2 ** (n - k))::bigint, (2 ** (n - k))::bigint from o
union all select 'superset_compact', itemset, 1, (2 ** (n - k))::bigint from o""")

    add("rules_order_mix_0_1", partial(_with, db=MIX, theta=0.1, fn=_rules), O.frequent(MIX, 0.1) + """
select (select string_agg(item, ',' order by item) from fi f where (b.s >> f.id) & 1 = 1) as body, fi.item as head, p.sup, round(p.sup / b.sup::double, 6) as confidence, round(p.sup / b.sup::double * (select m from m) / fi.c, 6) as lift
from ps p join fi on (p.s >> id) & 1 = 1 join ps b on b.s = xor(p.s, 1::bigint << id) where round(p.sup / b.sup::double, 9) >= 0.6""")
    add("area_top_order_mix_0_1", partial(_with, db=MIX, theta=0.1, fn=_area), O.frequent(MIX, 0.1) + """
select string_agg(item, ',' order by item) as itemset, bit_count(s)::int as size, any_value(sup) as sup, (any_value(sup) * bit_count(s))::bigint as area from ps join fi on (s >> id) & 1 = 1 where bit_count(s) >= 2 group by s order by area desc, itemset limit 20""")
    add("discriminative_label_attr_0_05", partial(_with, db="label_attr", theta=0.05, fn=_discriminative), O.frequent("label_attr", 0.05) + """,
e(x, t) as (select 0, 1), c as (select id, c as p, (1::bigint << id) as bit from fi where item = 'q=1'),
r as (select ps.s, ps.sup, coalesce((select sum(w) from g where (mask & (ps.s | bit)) = (ps.s | bit)), 0)::bigint as sup_pos, (select m from m)::double as m, p::double as p from ps, c where (ps.s & bit) = 0),
h as (select *, p / m as q0, sup_pos / sup::double as q1, case when m > sup then (p - sup_pos) / (m - sup) end as q2 from r)
select (select string_agg(item, ',' order by item) from fi where (s >> id) & 1 = 1) as itemset, bit_count(s)::int as size, sup, sup_pos,
 round((case when q0 <= 0 or q0 >= 1 then 0 else -q0 * log2(q0) - (1 - q0) * log2(1 - q0) end) - sup / m * (case when q1 <= 0 or q1 >= 1 then 0 else -q1 * log2(q1) - (1 - q1) * log2(1 - q1) end)
  - (m - sup) / m * (case when q2 is null or q2 <= 0 or q2 >= 1 then 0 else -q2 * log2(q2) - (1 - q2) * log2(1 - q2) end), 6) as info_gain from h""")
    nm = "(select string_agg(item, ',' order by item) from fi where ({} >> id) & 1 = 1)"
    add("overlap_pairs_user_day_0_05", partial(_with, db="user_day", theta=0.05, fn=_overlap), O.frequent("user_day", 0.05) + f""",
two as (select s from ps where bit_count(s) = 2)
select {nm.format('a.s')} as p, {nm.format('b.s')} as q, coalesce((select sum(w) from g where (mask & (a.s | b.s)) = (a.s | b.s)), 0)::bigint as overlap,
 round(coalesce((select sum(w) from g where (mask & (a.s | b.s)) = (a.s | b.s)), 0) / (select m from m)::double * bit_count(a.s & b.s), 6) as coverage2 from two a join two b on a.s < b.s""")
    add("cover_items_order_mix_0_2", partial(_with, db=MIX, theta=0.2, fn=_cover_items), O.frequent(MIX, 0.2) + " select u = n as covered, (n - u)::bigint as missing from (select (select count(distinct item) from tx) as n, (select bit_count(bit_or(s)) from mx) as u)")
    add("cover_trans_order_mix_0_2", partial(_with, db=MIX, theta=0.2, fn=_cover_rows), O.frequent(MIX, 0.2) + " select coalesce(sum(w), 0) = 0 as covered, coalesce(sum(w), 0)::bigint as missing from g where not exists (select 1 from mx where (g.mask & mx.s) = mx.s)")
    add("pattern_pair_part_attr_0_05", partial(_with, db="part_attr", theta=0.05, fn=_tiling), O.frequent("part_attr", 0.05) + f" select {nm.format('a.s')} as a, {nm.format('b.s')} as b, (a.sup * bit_count(a.s) + b.sup * bit_count(b.s))::bigint as area from ps a join ps b on a.s < b.s and (a.s & b.s) = 0")
    add("pattern_triples_part_attr_0_1", partial(_with, db="part_attr", theta=0.1, fn=_tiling3), O.frequent("part_attr", 0.1) + " select count(*) as sets, max(a.sup * bit_count(a.s) + b.sup * bit_count(b.s) + c.sup * bit_count(c.s))::bigint as best from ps a join ps b on a.s < b.s and (a.s & b.s) = 0 join ps c on b.s < c.s and (a.s & c.s) = 0 and (b.s & c.s) = 0")
    add("bounds_three_items_order_mix_0_2", partial(_with, db=MIX, theta=0.2, fn=_bounds), O.frequent(MIX, 0.2) + f""",
al as (select s, sup from ps union all select 0::bigint, (select m from m)),
dd as (select i.s, i.sup, j.s as j, sum(case when (bit_count(i.s) - bit_count(x.s)) % 2 = 1 then x.sup else -x.sup end) as v from ps i join al j on (i.s & j.s) = j.s and j.s <> i.s join al x on (i.s & x.s) = x.s and x.s <> i.s and (x.s & j.s) = j.s where bit_count(i.s) = 3 group by all)
select {nm.format('s')} as itemset, greatest(max(v) filter ((bit_count(s) - bit_count(j)) % 2 = 0), 0)::bigint as lower, (min(v) filter ((bit_count(s) - bit_count(j)) % 2 = 1))::bigint as upper, any_value(sup) as sup from dd group by s""")
    add("must_contain_order_mix_0_1", _must, O.frequent(MIX, 0.1) + named_where("(s & (select 1::bigint << id from fi where item = 'rf=N')) <> 0 and bit_count(s) <= 4"))
    attrs = {"p_type": "p_type", "size": "(p_size - 1) // 10", "cheap": "p_retailprice < 950"}
    subsets = [[x for k, x in enumerate(attrs) if code >> k & 1] for code in range(1, 8)]
    tests = " union all ".join(
        f"select '{','.join(sorted(x))}' as reduct, {len(x)}::int as size, (select count(*) from r a join r b on a.d < b.d and {' and '.join(f'a.{y} = b.{y}' for y in x)} where {' or '.join(f'a.{y} <> b.{y}' for y in attrs)}) as lost" for x in subsets)
    add("reducts_part", _reducts, f"with r as (select distinct {', '.join(f'{e} as {x}' for x, e in attrs.items())}, substr(p_brand, 1, 7) as d from part), t as ({tests}) select reduct, size from t where lost = 0 and size = (select min(size) from t where lost = 0)")
    add("model_order_mix_0_1", _model, O.frequent(MIX, 0.1) + named_where("(s & (select 1::bigint << id from fi where item = 'ls=F')) <> 0 and (s & (select bit_or(1::bigint << id) from fi where item = 'rf=A')) = 0 and (s & (select bit_or(1::bigint << id) from fi where item in ('rf=R', 'rf=N'))) <> 0 and bit_count(s) <= 4"))
    add("refine_order_mix_0_1", _refined, O.frequent(MIX, 0.2) + named_where("bit_count(s) >= 2"))
    add("enc_weighted_frequency_user_day", _weighted, O.base("user_day") + " select item, count(*) as masks, sum(w)::bigint as total, max(w) as most from fi join g on (mask >> id) & 1 = 1 group by item")
    ty, fl = ("(select bit_or(1::bigint << id) from fi where item like '" + x + "=%')" for x in ("type", "rf"))
    add("selected_expressions_order_mix_0_1", partial(_with, db=MIX, theta=0.1, fn=_selected), O.frequent(MIX, 0.1) + named_where(
        f"(s & {ty}) <> 0 and bit_count(s & {fl}) <= bit_count(s & {ty}) and (s & ~{ty}) <> 0 and 2 * bit_count(s & {fl}) + 0.5 * bit_count(s & ~{fl}) - 1.5 * bit_count(s & {fl}) <= 1.5 and bit_count(s & ~(select 1::bigint << id from fi where item = 'ls=F')) >= 2"))
    add("set_algebra", _set_algebra, """with t as (select p::bigint as p, q::bigint as q from range(32) a(p), range(32) b(q))
select p, q, p = q as equal, (p >> 3) & 1 = 1 as member, p & ~q as difference, p & q as intersection, p | q as union_, (p | q) = 31 as all_items, (p & q) = 0 as disjoint, (p & ~q) = 0 as inside from t""")
    add("expression_cnf", _expression, """with t as (select c::bigint as code, (c & 1) = 1 as a, (c & 2) = 2 as b, (c & 4) = 4 as d from range(8) r(c))
select code, a = (b or (not d and (not b or d))) as holds from t""")
    add("sum_propagators", _propagators, """with t as (select c, [(c // 27) % 3, (c // 9) % 3, (c // 3) % 3, c % 3] as s from range(81) r(c)),
b as (select c, list_sum([case when s[k] = 2 then [3, 2, 2, 1][k] else 0 end for k in [1, 2, 3, 4]])::bigint as lower, list_sum([case when s[k] <> 1 then [3, 2, 2, 1][k] else 0 end for k in [1, 2, 3, 4]])::bigint as upper from t)
select c::bigint as code, lower, upper, case when lower >= 5 then true when upper < 5 then false end as decided, upper < 5 as out from b""")
    witness = ", ".join(f"({i}, '{r}')" for i, r in enumerate(freqsat.WITNESS))
    cons = ", ".join(f"('{','.join(c)}', {lo}::double, {hi}::double)" for c, lo, hi in ((c, eval_fraction(lo), eval_fraction(hi)) for c, lo, hi in freqsat.WORKED))
    add("freqsat_worked_check", _freqsat_check, f"""with r(t, row) as (values {witness}), c(itemset, lo, hi) as (values {cons}),
h as (select itemset, lo, hi, count(*) filter (len(list_filter(string_split(itemset, ','), lambda x: not contains(row, x))) = 0) as sup from r, c group by all)
select itemset, sup, round(sup / 8.0, 6)::double as freq, sup / 8.0 >= lo - 1e-12 and sup / 8.0 <= hi + 1e-12 as ok from h""")
    add("freqsat_solve", _freqsat)
    add("freqsat_decided", _freqsat_decided, "select * from (values ('worked', 'yes', true), ('three_disjoint_halves', 'no', null), ('two_disjoint_halves', 'yes', true), ('rule_kept', 'yes', true), ('rule_broken', 'no', null)) v(instance, status, witness_ok)")
    add("local_vote_line_attr_0_05", partial(_vote, db="line_attr", theta=0.05), O.frequent_sql("line_attr", 0.05))
    add("stream_day_items", _stream, "select strftime(ts, '%Y-%m-%d') as day, event_type, count(*) as n from events group by all")
    add("generate_20x500", _generated, generate_sql(20, 500, 0.3, 0.4, 7))
    add("maximal_wide_70x200", _wide)
    for db in (MIX, "line_attr", EMB):
        add(f"advisor_{db}", partial(_advice, db=db), O.base(db) + """, d as (select round((select sum(c) from fi) / (m * (select count(*) from fi))::double, 6) as density from m)
select density, theta, case when theta <= case when density >= 0.45 then 0.10 else 0.04 end then 'growing' when theta between 0.10 and 0.25 then 'dual' else 'baseline' end as method,
case when theta > 0.2 then 'reduced' else 'clausal' end as coverage, case when theta <= 0.2 then 'pos' else 'neg' end as polarity
from d, (select unnest([0.01, 0.04, 0.05, 0.1, 0.2, 0.25, 0.3, 0.6])::double as theta)""")
    add("auto_order_mix_0_2", partial(_auto, db=MIX, theta=0.2), mx)
    add("cube_line_attr", _cube, O.frequent("line_attr", 3000) + " select string_agg(item, ',' order by item) as itemset, any_value(sup) as sup from ps join fi on (s >> id) & 1 = 1 group by s")
    add("length_bounds_order_mix", _lengths, O.base(MIX) + ", h as (select bit_count(mask)::int as size, sum(w)::bigint as rows from g group by 1) select size, rows, sum(rows) over (order by size desc)::bigint as at_least from h")
    add("search_times_order_mix", partial(_trace, fn=trace.search_times))
    add("blocking_growth_order_mix", partial(_trace, fn=trace.blocking_growth))
    add("beta_alpha_ratio_order_mix", partial(_trace, fn=trace.beta_alpha_ratio))
    add("restriction_overhead_order_mix", _overhead)
    add("solver_conflicts_order_mix", partial(_trace, fn=trace.conflicts))
    add("plan_cost_order_mix_0_2", _plan_cost)
    add("run_cost_order_mix_0_2", _run_cost)
    rules = """
select (select string_agg(item, ',' order by item) from fi f where (b.s >> f.id) & 1 = 1) as body, (select string_agg(item, ',' order by item) from fi f where (h.s >> f.id) & 1 = 1) as head, p.sup, round(p.sup / b.sup::double, 6) as confidence, round(p.sup / b.sup::double * (select m from m) / h.sup, 6) as lift
from ps p join ps b on (p.s & b.s) = b.s and b.s <> p.s join ps h on h.s = xor(p.s, b.s) where round(p.sup / b.sup::double, 9) >= 0.5"""
    add("rules_any_head_order_mix_0_1", partial(_with, db=MIX, theta=0.1, fn=_rules_any), O.frequent(MIX, 0.1) + rules)
    add("rules_line_attr_0_02", partial(_with, db="line_attr", theta=0.02, fn=_rules_any), O.frequent("line_attr", 0.02) + rules)
    add("rules_order_brand_0_01", partial(_with, db="order_brand", theta=0.01, fn=_rules_low), O.base("order_brand", 0.01) + """,
k as (select tid, item from tx join fi using (item)), p2 as (select a.tid, a.item as x, b.item as y from k a join k b on a.tid = b.tid and a.item < b.item),
f2 as (select x, y, count(*)::bigint as sup from p2 group by all having count(*) >= (select minsup from ms)),
f3 as (select p2.x, p2.y, c.item as z, count(*)::bigint as sup from p2 join k c on c.tid = p2.tid and c.item > p2.y group by all having count(*) >= (select minsup from ms)),
fs as (select item as s, c::bigint as sup from fi union all select x || ',' || y, sup from f2 union all select x || ',' || y || ',' || z, sup from f3),
r as (select x as body, y as head, sup from f2 union all select y, x, sup from f2
  union all select x, y || ',' || z, sup from f3 union all select y, x || ',' || z, sup from f3 union all select z, x || ',' || y, sup from f3
  union all select y || ',' || z, x, sup from f3 union all select x || ',' || z, y, sup from f3 union all select x || ',' || y, z, sup from f3)
select body, head, r.sup, round(r.sup / b.sup::double, 6) as confidence, round(r.sup / b.sup::double * (select m from m) / h.sup, 6) as lift from r join fs b on b.s = body join fs h on h.s = head where round(r.sup / b.sup::double, 9) >= 0.1""")
    cov = "(select coalesce(sum(w), 0) from g where {})"
    add("clusters_part_attr_0_05", partial(_with, db="part_attr", theta=0.05, fn=_clusters), O.frequent("part_attr", 0.05) + f" select {nm.format('a.s')} as a, {nm.format('b.s')} as b, (a.sup + b.sup)::bigint as rows from ps a join ps b on a.s < b.s where a.sup + b.sup = (select m from m) and {cov.format('(mask & (a.s | b.s)) = (a.s | b.s)')} = 0")
    add("concepts_part_attr_0_05", partial(_with, db="part_attr", theta=0.05, fn=_concepts), O.frequent("part_attr", 0.05) + f""",
cl as (select 1::bigint << id as bit from fi where item = 'pr=lo'),
pu as (select s from ps, cl where (s & bit) = 0 and bit_count(s) <= 2 and sup > 0 and sup = {cov.format('(mask & (ps.s | bit)) = (ps.s | bit)')})
select {nm.format('a.s')} as a, {nm.format('b.s')} as b, {cov.format('(mask & bit) = bit and ((mask & a.s) = a.s or (mask & b.s) = b.s)')}::bigint as covered from pu a join pu b on a.s < b.s, cl""")
    add("redescriptions_order_mix_0_1", partial(_with, db=MIX, theta=0.1, fn=_redescriptions), O.frequent(MIX, 0.1) + f""",
vw as (select bit_or(1::bigint << id) as v from fi where item like 'type=%'), pq as (select a.s as p, b.s as q, a.sup as sp, b.sup as sq, {cov.format('(mask & (a.s | b.s)) = (a.s | b.s)')}::bigint as together from ps a, ps b, vw where (a.s & v) = a.s and (b.s & v) = 0)
select {nm.format('p')} as p, {nm.format('q')} as q, together, round(together / (sp + sq - together)::double, 6) as jaccard from pq where round(together / (sp + sq - together)::double, 9) >= 0.3""")
    bit = lambda *names: "(select bit_or(1::bigint << id) from fi where item in (" + ", ".join(f"'{x}'" for x in names) + "))"
    for key, kw, cond in (
        ("must_not", {"must_not": ["rf=N", "ls=O"]}, f"(s & {bit('rf=N', 'ls=O')}) = 0"), ("any_of", {"any_of": [["rf=A", "rf=R"], ["ls=F", "ls=O"]]}, f"(s & {bit('rf=A', 'rf=R')}) <> 0 and (s & {bit('ls=F', 'ls=O')}) <> 0"),
        ("max_size_2", {"max_size": 2}, "bit_count(s) <= 2"), ("max_weight", {"weights": {"rf=N": 2.0, "ls=O": 1.0, "ls=F": 1.0}, "max_weight": 2.0}, f"2 * bit_count(s & {bit('rf=N')}) + bit_count(s & {bit('ls=O', 'ls=F')}) <= 2"),
    ):
        add(f"{key}_order_mix_0_1", partial(_bounded, **kw), O.frequent(MIX, 0.1) + named_where(cond))
    add("exactness_order_mix_0_2", _exactness, "select method, 0::bigint as missing, 0::bigint as extra from (values ('growing'), ('length'), ('dual'), ('bitset'), ('propagation'), ('frontier')) v(method)")
    parts = "\nunion all\n".join(f"select '{x}' as db, {t}::double as theta, (select count(*) from ({O.frequent(x, t)} select * from mx)) as n_maximal" for x in ("user_day", "part_attr") for t in workloads.SWEEP)
    add("phase_transition_borders", _transition, f"select db, theta, n_maximal from (select *, row_number() over (partition by db order by n_maximal desc, theta) as r from ({parts})) where r = 1")
    add("phase_transition_seconds", _transition_seconds)
    for n in (70, 120):
        add(f"freq_wide_{n}_size_3", partial(_wide_sets, n=n), _wide_sql(n))
        add(f"levelwise_wide_{n}_size_3", partial(_wide_sets, n=n, engine="levelwise"), _wide_sql(n))
    for key, fn in workloads.full_grids().items():
        add(key, fn)
    for key, (fn, oracle) in workloads.queries().items():
        add(key, fn, oracle)
    return q, sql


def named_where(cond: str) -> str:
    return O.named("(select * from ps where " + cond + ")")


def eval_fraction(x: str) -> float:
    from fractions import Fraction

    return float(Fraction(x))
