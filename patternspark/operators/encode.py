"""Boolean encodings as relations, written as DataFrame plans.

A formula is ``cid, family, op, bound, lits`` with ``lits ARRAY<STRUCT<var, neg, coef>>``; item variables are called
``I_name``, row variables ``T_tid``. Transactions come as ``tid, items``; the alphabet is a list, so absent items are
an array difference inside each row and no item is ever shuffled for coverage. Frequency groups rows by item once.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import bits

SCHEMA = "cid bigint, family string, op string, bound bigint, lits array<struct<var:string,neg:boolean,coef:bigint>>"


def _lit(var: Column, neg: bool, coef: Column | int = 1) -> Column:
    c = coef if isinstance(coef, Column) else F.lit(coef)
    return F.struct(var.alias("var"), F.lit(neg).alias("neg"), c.cast("long").alias("coef"))


def _item(name: Column) -> Column:
    return F.concat(F.lit("I_"), name)


def _row(tid: Column) -> Column:
    return F.concat(F.lit("T_"), tid.cast("string"))


def _each(names: list[str], fn) -> Column:
    return F.transform(F.array(*[F.lit(x) for x in names]), fn)


def _formula(df: DataFrame, family: str, op: str, bound: Column | int, lits: Column) -> DataFrame:
    b = bound if isinstance(bound, Column) else F.lit(bound)
    return df.select(F.lit(family).alias("family"), F.lit(op).alias("op"), b.cast("long").alias("bound"), lits.alias("lits"))


def numbered(df: DataFrame) -> DataFrame:
    return df.select(F.monotonically_increasing_id().alias("cid"), "family", "op", "bound", "lits")


def _rows(tx: DataFrame, names: list[str]) -> DataFrame:
    alphabet = F.array(*[F.lit(x) for x in sorted(names)])
    return tx.select("tid", "items", F.array_except(alphabet, F.col("items")).alias("absent"))


def coverage(tx: DataFrame, names: list[str], kind: str = "clausal") -> DataFrame:
    """Row variables stand for their coverage. 'clausal': a binary clause per absent item and a long one per row;
    'reduced': one inequality instead of a row's binary clauses; 'positive': no negated literal anywhere."""
    rows = _rows(tx, names)
    t = _row(F.col("tid"))
    some = F.concat(F.array(_lit(t, False)), F.transform("absent", lambda i: _lit(_item(i), False)))
    if kind == "positive":
        long_ = _formula(rows, "coverage_long", ">=", 1, some)
        pair = rows.select("tid", F.explode("absent").alias("i"))
        return long_.union(_formula(pair, "coverage_pair", "<=", 1, F.array(_lit(_row(F.col("tid")), False), _lit(_item(F.col("i")), False))))
    long_ = _formula(rows, "coverage_long", "or", 1, some)
    if kind == "clausal":
        pair = rows.select("tid", F.explode("absent").alias("i"))
        return long_.union(_formula(pair, "coverage_binary", "or", 1, F.array(_lit(_row(F.col("tid")), True), _lit(_item(F.col("i")), True))))
    if kind == "reduced":
        size = F.size("absent")
        sums = F.concat(F.array(_lit(t, True, size)), F.transform("absent", lambda i: _lit(_item(i), False, -1)))
        return long_.union(_formula(rows.where(size > 0), "coverage_sum", ">=", 0, sums))
    raise ValueError(kind)


def frequency(tx: DataFrame, names: list[str], minsup: int, kind: str = "reified") -> DataFrame:
    """'reified': an inequality per item over its rows, lifted where the item is not chosen; 'plain': one over all rows;
    'positive': the reified one without negation. Items that never occur keep their (unsatisfiable unless lifted) row."""
    spark = tx.sparkSession
    if kind == "plain":
        one = tx.agg(F.array_sort(F.collect_list(_row(F.col("tid")))).alias("rows"))
        return _formula(one, "frequency", ">=", minsup, F.transform("rows", lambda t: _lit(t, False)))
    alphabet = spark.createDataFrame([(x,) for x in sorted(names)], "i string")
    own = tx.select("tid", F.explode("items").alias("i")).groupBy("i").agg(F.array_sort(F.collect_list(_row(F.col("tid")))).alias("rows"))
    per = alphabet.join(own, "i", "left").select("i", F.coalesce("rows", F.array().cast("array<string>")).alias("rows"))
    rows = F.transform("rows", lambda t: _lit(t, False))
    item = _item(F.col("i"))
    if kind == "reified":
        return _formula(per, "frequency", ">=", minsup, F.concat(F.array(_lit(item, True, minsup)), rows))
    if kind == "positive":
        return _formula(per, "frequency", ">=", 0, F.concat(F.array(_lit(item, False, -minsup)), rows))
    raise ValueError(kind)


def weighted_frequency(masks: DataFrame, names: list[str], minsup: int) -> DataFrame:
    """The reified form on collapsed rows (``mask, w``): the row variable of a mask has its weight as coefficient."""
    spread = masks.select("mask", "w", F.explode(bits.items_of(F.col("mask"), len(names))).alias("k"))
    per = spread.groupBy("k").agg(F.array_sort(F.collect_list(F.struct(F.col("mask"), F.col("w")))).alias("rows"))
    table = F.array(*[F.lit(x) for x in names])
    rows = F.transform("rows", lambda r: _lit(_row(F.array_join(r["mask"], "_") if bits.is_wide(len(names)) else r["mask"]), False, r["w"]))
    return _formula(per, "frequency", ">=", minsup, F.concat(F.array(_lit(_item(F.element_at(table, F.col("k") + 1)), True, minsup)), rows))


def nonempty(tx: DataFrame, names: list[str]) -> DataFrame:
    """Some item is chosen; without it the reified frequency admits the empty itemset."""
    one = tx.sparkSession.range(1)
    return _formula(one, "nonempty", "or", 1, _each(sorted(names), lambda i: _lit(_item(i), False)))


def core(tx: DataFrame, names: list[str], minsup: int, *, kind: str = "clausal", freq: str = "reified") -> DataFrame:
    """Coverage, frequency and the non-empty clause: the whole mining formula."""
    out = coverage(tx, names, kind).union(frequency(tx, names, minsup, "positive" if kind == "positive" and freq == "reified" else freq))
    return numbered(out.union(nonempty(tx, names)))


def dual(tx: DataFrame, names: list[str], minsup: int, kind: str = "clausal") -> DataFrame:
    """Models are the infrequent itemsets: coverage as before, at most ``minsup - 1`` rows."""
    one = tx.agg(F.array_sort(F.collect_list(_row(F.col("tid")))).alias("rows"))
    low = _formula(one, "infrequency", "<=", minsup - 1, F.transform("rows", lambda t: _lit(t, False)))
    return numbered(coverage(tx, names, kind).union(low).union(nonempty(tx, names)))


def maximality(tx: DataFrame, names: list[str], minsup: int, m: int) -> DataFrame:
    """An item that is left out reaches fewer than ``minsup`` of the covered rows."""
    alphabet = tx.sparkSession.createDataFrame([(x,) for x in sorted(names)], "i string")
    own = tx.select("tid", F.explode("items").alias("i")).groupBy("i").agg(F.array_sort(F.collect_list(_row(F.col("tid")))).alias("rows"))
    per = alphabet.join(own, "i", "left").select("i", F.coalesce("rows", F.array().cast("array<string>")).alias("rows"))
    lits = F.concat(F.array(_lit(_item(F.col("i")), False, m - minsup + 1)), F.transform("rows", lambda t: _lit(t, False, -1)))
    return _formula(per, "maximality", ">=", 1 - minsup, lits)


def restrict_incremental(formula: DataFrame, names: list[str]) -> DataFrame:
    """Companion variables N_i with (I_i or N_i): assumptions on N do what removing clauses would."""
    one = formula.sparkSession.createDataFrame([(x,) for x in sorted(names)], "i string")
    more = _formula(one, "companion", "or", 1, F.array(_lit(_item(F.col("i")), False), _lit(F.concat(F.lit("N_"), F.col("i")), False)))
    return numbered(formula.select("family", "op", "bound", "lits").union(more))


def restrict_fixed(formula: DataFrame, names: list[str]) -> DataFrame:
    """As above and one sum with a control variable y: y + sum(I) + sum(N) >= n + 1. No clause is ever added later."""
    base = restrict_incremental(formula, names).select("family", "op", "bound", "lits")
    one = formula.sparkSession.range(1)
    lits = F.concat(F.array(_lit(F.lit("y"), False)), _each(sorted(names), lambda i: _lit(_item(i), False)), _each(sorted(names), lambda i: _lit(F.concat(F.lit("N_"), i), False)))
    return numbered(base.union(_formula(one, "control", ">=", len(names) + 1, lits)))


def length(names: list[str], formula: DataFrame, size: int | None = None) -> DataFrame:
    """Sizes by assumption (sum(I) + sum(A) = n), or one direct equality sum(I) = size."""
    one = formula.sparkSession.range(1)
    items = _each(sorted(names), lambda i: _lit(_item(i), False))
    if size is not None:
        row = _formula(one, "size", "=", size, items)
    else:
        row = _formula(one, "length", "=", len(names), F.concat(items, _each(sorted(names), lambda i: _lit(F.concat(F.lit("A_"), i), False))))
    return numbered(formula.select("family", "op", "bound", "lits").union(row))


def cardinality_cnf(tx: DataFrame, names: list[str], minsup: int, method: str = "seqcounter") -> DataFrame:
    """CNF for "an item that is chosen has at least ``minsup`` rows", guarded by the item.

    All variables may be true only if enough rows are, so that the last one forces the count. 'seqcounter': s(j, k) needs
    k of the item's first j rows. 'bdd': a decision diagram over (row, count) with only the nodes that are reachable
    and can still end well. 'totalizer': a tree of unary sums, each node's k-th output needs k of its rows. 'network':
    odd-even merge sorting, whose output k needs k rows. Small databases only.
    """
    if method not in ("seqcounter", "bdd", "totalizer", "network"):
        raise ValueError(method)
    per = tx.select("tid", F.explode("items").alias("i")).groupBy("i").agg(F.array_sort(F.collect_list("tid")).alias("tids")).select("i", "tids", F.size("tids").alias("c"))
    unit = _formula(per.where(F.col("c") < minsup), "count_unit", "or", 1, F.array(_lit(_item(F.col("i")), True)))
    ok = per.where(F.col("c") >= minsup)
    if method in ("totalizer", "network"):
        return numbered(unit.union(_totalizer(ok, minsup) if method == "totalizer" else _network(ok, minsup)))
    name = lambda j, k: F.concat(F.lit("s_"), F.col("i"), F.lit("_"), j.cast("string"), F.lit("_"), k.cast("string"))
    cells = ok.select("i", "tids", "c", F.posexplode("tids").alias("p", "tid")).select("*", (F.col("p") + 1).alias("j"), F.explode(F.sequence(F.lit(1), F.lit(minsup))).alias("k"))
    if method != "seqcounter":  # from a state that cannot reach the end, or cannot be reached, no node is needed
        cells = cells.where((F.col("k") <= F.col("j")) & (F.col("k") >= F.lit(minsup) - (F.col("c") - F.col("j"))))
    else:
        cells = cells.where(F.col("k") <= F.col("j"))
    here, t = _lit(name(F.col("j"), F.col("k")), True), _lit(_row(F.col("tid")), False)
    before = _lit(name(F.col("j") - 1, F.col("k")), False)
    less = _lit(name(F.col("j") - 1, F.col("k") - 1), False)
    # s(j,k) -> s(j-1,k) or T_j        s(j,k) -> s(j-1,k) or s(j-1,k-1)
    stay = F.when(F.col("j") > F.col("k"), F.array(here, before, t)).otherwise(F.array(here, t))
    step = F.when(F.col("j") > F.col("k"), F.array(here, before, less)).otherwise(F.array(here, less))
    goal = F.array(_lit(_item(F.col("i")), True), _lit(name(F.col("c"), F.lit(minsup)), False))
    return numbered(
        unit.union(_formula(cells, "count_row", "or", 1, stay)).union(_formula(cells.where(F.col("k") > 1), "count_step", "or", 1, step)).union(_formula(ok, "count_goal", "or", 1, goal))
    )


def _totalizer(ok: DataFrame, minsup: int) -> DataFrame:
    """Clauses of a unary tree over each item's rows: block b of level l sums rows b * 2^l up to the next block.

    An output of a node with more than i + j true rows needs more than i below on the left or more than j on the right.
    """
    top = F.ceil(F.log2(F.col("c"))).cast("int")
    out = lambda l, b, k: F.when(l == 0, _row(F.get("tids", b))).otherwise(F.concat(F.lit("u_"), F.col("i"), F.lit("_"), l.cast("string"), F.lit("_"), b.cast("string"), F.lit("_"), k.cast("string")))
    width = lambda l, b: F.greatest(F.lit(0), F.least(F.col("c") - b * bits_shift(l), bits_shift(l))).cast("int")
    nodes = ok.where("c > 1").select("i", "tids", "c", F.explode(F.sequence(F.lit(1), top)).alias("l")).select("*", F.explode(F.sequence(F.lit(0), F.floor((F.col("c") - 1) / bits_shift(F.col("l"))).cast("int"))).alias("b"))
    nodes = nodes.withColumn("wa", width(F.col("l") - 1, F.col("b") * 2)).withColumn("wb", width(F.col("l") - 1, F.col("b") * 2 + 1))
    cells = nodes.select("*", F.explode(F.sequence(F.lit(0), F.least("wa", F.lit(minsup)))).alias("x")).select("*", F.explode(F.sequence(F.lit(0), F.least("wb", F.lit(minsup)))).alias("y")).where((F.col("x") + F.col("y") < F.least(F.col("wa") + F.col("wb"), F.lit(minsup))))
    l, b, x, y = (F.col(v) for v in ("l", "b", "x", "y"))
    none = F.array().cast("array<struct<var:string,neg:boolean,coef:bigint>>")
    lits = F.concat(F.array(_lit(out(l, b, x + y + 1), True)), F.when(x < F.col("wa"), F.array(_lit(out(l - 1, b * 2, x + 1), False))).otherwise(none), F.when(y < F.col("wb"), F.array(_lit(out(l - 1, b * 2 + 1, y + 1), False))).otherwise(none))
    goal = F.array(_lit(_item(F.col("i")), True), _lit(out(F.when(F.col("c") > 1, top).otherwise(0), F.lit(0), F.lit(minsup)), False))
    return _formula(cells, "count_node", "or", 1, lits).union(_formula(ok, "count_goal", "or", 1, goal))


def bits_shift(level):
    """2 to the power of a column, as a whole number."""
    return F.call_function("shiftleft", F.lit(1), level.cast("int"))


def merge_network(wires: int) -> list[tuple[int, int, int]]:
    """(step, a, b) comparators of odd-even merge sorting of a power of two of wires; the greater value goes to a < b."""
    out, step = [], 0
    p = 1
    while p < wires:
        k = p
        while k >= 1:
            for j in range(k % p, wires - k, 2 * k):
                for i in range(min(k, wires - j - k)):
                    if (i + j) // (2 * p) == (i + j + k) // (2 * p):
                        out.append((step, i + j, i + j + k))
            step += 1
            k //= 2
        p *= 2
    return out


#: Most rows of an item that a sorting network is built for.
MAX_WIRES = 4096


def _network(ok: DataFrame, minsup: int) -> DataFrame:
    """Clauses of a sorting network over each item's rows, padded by wires that are false."""
    spark = ok.sparkSession
    sizes = sorted(r[0] for r in ok.select(F.greatest(F.lit(1), bits_shift(F.ceil(F.log2("c")))).alias("p")).distinct().collect())  # powers of two
    if sizes and sizes[-1] > MAX_WIRES:
        raise ValueError(f"an item of more than {MAX_WIRES} rows")
    plan, last = [], []
    for p in sizes:
        at = {w: 0 for w in range(p)}  # how often each wire was compared
        for _, a, b in merge_network(p):
            plan.append((p, a, b, at[a], at[b]))
            at[a], at[b] = at[a] + 1, at[b] + 1
        last += [(p, w, k) for w, k in at.items()]
    table = spark.createDataFrame(plan, "p int, a int, b int, ta int, tb int")
    wired = ok.withColumn("p", F.greatest(F.lit(1), bits_shift(F.ceil(F.log2("c")))))
    name = lambda w, t: F.when(t == 0, F.coalesce(_row(F.get("tids", w)), F.concat(F.lit("none_"), F.col("i")))).otherwise(F.concat(F.lit("w_"), F.col("i"), F.lit("_"), w.cast("string"), F.lit("_"), t.cast("string")))
    on = wired.join(F.broadcast(table), "p")  # a few thousand comparators a size
    a, b = name(F.col("a"), F.col("ta")), name(F.col("b"), F.col("tb"))
    most, least = name(F.col("a"), F.col("ta") + 1), name(F.col("b"), F.col("tb") + 1)
    ends = spark.createDataFrame(last, "p int, w int, t int").where(F.col("w") == minsup - 1)
    goal = wired.join(F.broadcast(ends), "p")
    return (
        _formula(on, "count_most", "or", 1, F.array(_lit(most, True), _lit(a, False), _lit(b, False)))
        .union(_formula(on, "count_least", "or", 1, F.array(_lit(least, True), _lit(a, False))))
        .union(_formula(on, "count_least", "or", 1, F.array(_lit(least, True), _lit(b, False))))
        .union(_formula(wired.where(F.col("p") > F.col("c")), "count_none", "or", 1, F.array(_lit(F.concat(F.lit("none_"), F.col("i")), True))))
        .union(_formula(goal, "count_goal", "or", 1, F.array(_lit(_item(F.col("i")), True), _lit(name(F.col("w"), F.col("t")), False))))
    )


def formula_size(formula: DataFrame) -> DataFrame:
    """One row: ``variables, binary, long, pb, literals, longest``. Clauses of two literals are binary, others long."""
    clause, n = F.col("op") == "or", F.size("lits")
    counts = formula.agg(
        F.sum((clause & (n == 2)).cast("long")).alias("binary"), F.sum((clause & (n != 2)).cast("long")).alias("long"), F.sum((~clause).cast("long")).alias("pb"),
        F.sum(n.cast("long")).alias("literals"), F.max(n).cast("long").alias("longest"),
    )
    variables = formula.select(F.explode("lits.var").alias("v")).distinct().agg(F.count(F.lit(1)).alias("variables"))
    return variables.crossJoin(counts)


def opb_lines(formula: DataFrame) -> DataFrame:
    """``cid, value``: each constraint as a line of a pseudo-Boolean file (``~x`` for negation, clauses as sums)."""
    term = F.transform("lits", lambda x: F.concat(F.when(x["coef"] >= 0, "+").otherwise(""), x["coef"].cast("string"), F.when(x["neg"], " ~").otherwise(" "), F.regexp_replace(x["var"], "[^A-Za-z0-9_]", "_")))
    op = F.when(F.col("op") == "or", ">=").otherwise(F.col("op"))
    return formula.select("cid", F.concat(F.array_join(term, " "), F.lit(" "), op, F.lit(" "), F.col("bound").cast("string"), F.lit(" ;")).alias("value"))


def cnf_lines(formula: DataFrame) -> DataFrame:
    """``cid, value``: clauses in DIMACS form; variables are numbered by name. Only clauses can be written."""
    clauses = formula.where("op = 'or'").select("cid", F.posexplode("lits").alias("p", "x"))
    names = clauses.select(F.col("x.var").alias("var")).distinct()
    numbered_ = names.select("var", F.dense_rank().over(_window()).alias("number"))
    out = clauses.select("cid", "p", F.col("x.var").alias("var"), F.col("x.neg").alias("neg")).join(numbered_, "var")
    signed = F.struct("p", (F.when(F.col("neg"), -1).otherwise(1) * F.col("number")).cast("string").alias("s"))
    return out.groupBy("cid").agg(F.array_sort(F.collect_list(signed)).alias("l")).select("cid", F.concat(F.array_join("l.s", " "), F.lit(" 0")).alias("value"))


def _window():
    from pyspark.sql import Window

    return Window.orderBy("var")


def write_opb(formula: DataFrame, path: str) -> None:
    opb_lines(formula).select("value").write.mode("overwrite").text(path)


def write_cnf(formula: DataFrame, path: str) -> None:
    cnf_lines(formula).select("value").write.mode("overwrite").text(path)
