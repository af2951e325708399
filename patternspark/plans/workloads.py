"""The experiment workloads: grids of databases, thresholds and configurations, each as one distributed job.

A cell is a (database, threshold, configuration). The collapsed rows of a database are paired with its cells and every
cell runs in a group of its own, so a grid uses the whole cluster and a cell that exhausts its budget only reports so.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.util import inheritable_thread_target

from ..functions import bits
from ..operators import blocking as B
from ..operators.formula import Matrix
from ..operators.itemdb import ItemDB, build_item_db, profile
from ..operators.partition import Kernel
from ..operators.search import Options, Scope, search_counts
from ..operators.solver import PROFILES, Polarity, SolverParams, SolverProfile
from ..sources import databases as D
from ..sources.generator import generate, generate_sql
from . import oracles as O

GRID = "db string, theta double, config string, status string, seconds double, searches long, alpha long, beta long, unsat long, n_found long, n_maximal long, longest int, conflicts long, blockers long, literals long, decisions long, backtracks long, restarts long"


#: Distinct rows of a grid's database.
MOST_ROWS = 1_000_000


@dataclass(frozen=True)
class Config:
    """A named configuration; ``everything``: it reports all frequent sets, of which the maximal ones are counted."""

    name: str
    kernel: Kernel
    everything: bool = False


def clausal(name: str, *, everything: bool = False, **options) -> Config:
    return Config(name, Kernel("clausal", Options(**options)), everything)


CP = Config("cp", Kernel("propagation"), True)
NATIVE, JVM = clausal("native", profile=PROFILES["native"], restriction="incremental"), clausal("jvm", profile=PROFILES["jvm"])
BITSET = Config("bitset", Kernel("bitset"))
SEARCH = (clausal("simple", search="simple"), clausal("lsm", search="longest"), clausal("cmg"), clausal("ld", search="length"))


def run_grid(dbs: dict[str, ItemDB], thetas: Iterable[float] | dict[str, Iterable[float]], configs: Iterable[Config], *, seconds: float = 60) -> DataFrame:
    """One row a cell (see GRID). ``thetas`` may differ by database. A cell that spends its seconds reports so.

    A cell's rows are one task's: at most MOST_ROWS distinct ones (checked); larger databases are for ``mine``.
    """
    configs = {c.name: c for c in configs}
    spark = next(iter(dbs.values())).spark
    cells = [(name, float(t), c, db.minsup(t), db.n) for name, db in dbs.items() for t in (thetas[name] if isinstance(thetas, dict) else thetas) for c in configs]
    table = spark.createDataFrame(cells, "db string, theta double, config string, minsup long, n int")
    rows = None
    for name, db in dbs.items():
        if db.masks.count() > MOST_ROWS:
            raise ValueError(f"{name} has more than {MOST_ROWS} distinct rows")
        own = db.masks.select(F.lit(name).alias("db"), (F.col("mask") if bits.is_wide(db.n) else F.array("mask")).alias("mask"), "w")
        rows = own if rows is None else rows.union(own)
    paired = table.join(rows, "db", "left").repartition(min(len(cells), 2000), "db", "theta", "config")

    def run(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        import time
        from dataclasses import replace

        name, theta, config = key
        group = group.dropna(subset=["mask"])
        group = group.assign(mask=[bits.to_int(x) for x in group["mask"]]).sort_values("mask")
        c = configs[config]
        m = Matrix([int(x) for x in group["mask"]], [int(x) for x in group["w"]], int(group["n"].iloc[0]) if len(group) else 0)
        start = time.perf_counter()
        r = replace(c.kernel, seconds=seconds)(m, int(group["minsup"].iloc[0]), Scope()) if len(group) else None
        took = time.perf_counter() - start
        kinds = search_counts(r.trace) if r else {}
        found = r.found if r else {}
        border = _border(found) if c.everything else found
        add = lambda f: sum(v for k, v in kinds.items() if f(k))
        last = r.trace[-1] if r and r.trace else {"blockers": 0, "literals": 0}
        return pd.DataFrame([(name, theta, config, r.status if r else "ok", took, add(lambda k: True), kinds.get("alpha", 0), add(lambda k: k.startswith("beta")), add(lambda k: k.endswith("unsat")), len(found), len(border), max((x.bit_count() for x in border), default=0), sum(t["conflicts"] for t in r.trace) if r else 0, last["blockers"], last["literals"], *[sum(t.get(c, 0) for t in r.trace) if r else 0 for c in ("decisions", "backtracks", "restarts")])], columns=[x.split()[0] for x in GRID.split(", ")])

    return paired.groupBy("db", "theta", "config").applyInPandas(run, GRID)


def _border(found: dict[int, int]) -> dict[int, int]:
    """Maximal ones of a family that is closed under subsets: those that are no one-item-smaller subset."""
    below = {x & ~(1 << i) for x in found for i in bits.bits(x)}
    return {x: s for x, s in found.items() if x not in below}



#: Databases of a grid that are built at a time: the short jobs of one fill the ends of the others'.
BUILT_AT_ONCE = 4


def dbs(spark: SparkSession, sf_dir: str, names: Iterable[str]) -> dict[str, ItemDB]:
    names = list(names)
    with ThreadPoolExecutor(BUILT_AT_ONCE) as pool:
        made = [pool.submit(inheritable_thread_target(spark)(lambda x=x: D.item_db(spark, sf_dir, x))) for x in names]
        return {x: f.result() for x, f in zip(names, made)}


def generated(spark: SparkSession, specs: dict[str, tuple]) -> dict[str, ItemDB]:
    return {k: build_item_db(generate(spark, *v)) for k, v in specs.items()}


THETAS = (0.02, 0.05, 0.1, 0.2, 0.4)
ALL = ("line_attr", "order_attr", "order_mix", "user_day", "emb_sign8", "doc_words16", "part_attr", "cust_attr", "order_brand", "emb_sign16")


def w01_overall(spark, sf_dir, names=ALL, thetas=THETAS, seconds=60) -> DataFrame:
    """Overall time of two growing-search profiles and the propagation baseline."""
    return run_grid(dbs(spark, sf_dir, names), thetas, (NATIVE, JVM, CP), seconds=seconds)


DENSITY = {f"gen_d{int(100 * d)}": (20, 300, d, 0.3, 1) for d in (0.15, 0.3, 0.45, 0.6)}


def w02_density(spark, sf_dir="", specs=None, thetas=(0.1, 0.2, 0.4, 0.6), seconds=60) -> DataFrame:
    """Where the cost peaks over thresholds as density grows."""
    return run_grid(generated(spark, specs or DENSITY), thetas, (BITSET, CP), seconds=seconds)


def w03_low_threshold(spark, sf_dir, thetas=(0.01, 0.02, 0.05, 0.1), seconds=60) -> DataFrame:
    """Very low thresholds on dense data."""
    return run_grid(dbs(spark, sf_dir, ("emb_sign8",)), thetas, (BITSET, CP), seconds=seconds)


def w04_enumeration(spark, sf_dir, names=("order_mix",), thetas=(0.4, 0.6), seconds=60) -> DataFrame:
    """Optimisation and decision search under four kinds of blocking."""
    options = (B.FULL, B.ITEMS, B.SUBSETS, B.SUBSET)
    configs = [clausal(f"{s}_{b}", search=x, blocking=b, everything=b in (B.FULL, B.ITEMS)) for s, x in (("optimise", "longest"), ("decide", "simple")) for b in options]
    return run_grid(dbs(spark, sf_dir, names), thetas, configs, seconds=seconds)


CLASSES = {"gen_dense": (14, 120, 0.5, 0.2, 1), "gen_normal": (14, 120, 0.33, 0.2, 1), "gen_sparse": (14, 120, 0.18, 0.2, 1)}


def w05_search_by_density(spark, sf_dir="", specs=None, thetas=(0.2,), seconds=60) -> DataFrame:
    """Four searches on dense, normal and sparse generated data."""
    return run_grid(generated(spark, specs or CLASSES), thetas, SEARCH, seconds=seconds)


def w06_search_by_threshold(spark, sf_dir, names=("order_mix",), thetas=(0.2, 0.4), seconds=60) -> DataFrame:
    """Four searches over thresholds."""
    return run_grid(dbs(spark, sf_dir, names), thetas, SEARCH, seconds=seconds)


def w08_encodings(spark, sf_dir, names=("order_mix",), thetas=(0.2, 0.4, 0.6), seconds=60) -> DataFrame:
    """Clausal and reduced coverage, free and restricted to assumptions."""
    configs = [clausal(f"{c}_{r}", coverage=c, restriction=r) for c in ("clausal", "reduced") for r in ("free", "incremental")]
    return run_grid(dbs(spark, sf_dir, names), thetas, configs, seconds=seconds)


def w09_polarity(spark, sf_dir, names=("order_mix",), thetas=(0.1, 0.2, 0.4, 0.6), seconds=60) -> DataFrame:
    """Positive, negative and dynamic polarity."""
    return run_grid(dbs(spark, sf_dir, names), thetas, [clausal(p, profile=SolverProfile(polarity=Polarity(p))) for p in ("pos", "neg", "dynamic")], seconds=seconds)


def w10_profiles(spark, sf_dir, names=("order_mix",), thetas=(0.2, 0.4), seconds=60) -> DataFrame:
    """Solver profiles, the bitset engine and the baseline."""
    return run_grid(dbs(spark, sf_dir, names), thetas, (NATIVE, JVM, BITSET, CP), seconds=seconds)


def w11_characteristics(spark, sf_dir, names=ALL) -> DataFrame:
    """Profile of every database."""
    out = None
    for name, db in dbs(spark, sf_dir, names).items():
        own = profile(db).select(F.lit(name).alias("db"), "*")
        out = own if out is None else out.union(own)
    return out


ITEMS = {f"gen_n{n}": (n, 300, 0.3, 0.3, 1) for n in (8, 12, 16)}
ROWS = {f"gen_m{m}": (12, m, 0.3, 0.3, 1) for m in (100, 1000, 10000)}


def w12_items(spark, sf_dir="", specs=None, thetas=(0.1, 0.2), seconds=60) -> DataFrame:
    """Scaling in the number of items."""
    return run_grid(generated(spark, specs or ITEMS), thetas, (clausal("cmg"), BITSET, CP), seconds=seconds)


def w13_rows(spark, sf_dir="", specs=None, thetas=(0.2, 0.4), seconds=60) -> DataFrame:
    """Scaling in the number of rows."""
    return run_grid(generated(spark, specs or ROWS), thetas, (BITSET, CP), seconds=seconds)


SWEEP = tuple(round(0.01 * k, 2) for k in range(1, 81))


def w14_sweep(spark, sf_dir, names=("user_day", "part_attr"), thetas=SWEEP, seconds=60) -> DataFrame:
    """A fine sweep of thresholds."""
    return run_grid(dbs(spark, sf_dir, names), thetas, (BITSET, CP), seconds=seconds)


def w16_dual(spark, sf_dir, names=("order_mix",), thetas=(0.1, 0.15, 0.2, 0.25), seconds=60) -> DataFrame:
    """Minimal infrequent sets (``n_found``) where the dual is advised, beside the growing search."""
    return run_grid(dbs(spark, sf_dir, names), thetas, (clausal("dual", search="dual", blocking=B.SUPERSET), clausal("cmg")), seconds=seconds)


def w17_single(spark, sf_dir, names=("order_mix", "user_day", "part_attr", "emb_sign8"), thetas=(0.1, 0.4), seconds=60) -> DataFrame:
    """One search of each profile, the black-box one included."""
    return run_grid(dbs(spark, sf_dir, names), thetas, [clausal(k, search="decide", profile=p) for k, p in PROFILES.items()], seconds=seconds)


def w_parameters(spark, sf_dir, names=("order_mix",), thetas=(0.2,), seconds=60) -> DataFrame:
    """Sensitivity to decay and branching."""
    configs = [clausal(f"decay_{d}_{b}", profile=SolverProfile(params=SolverParams(var_decay=d, branch=b))) for d in (0.8, 0.95) for b in ("items_first", "any")]
    return run_grid(dbs(spark, sf_dir, names), thetas, configs, seconds=seconds)


# The same at full size: all databases and thresholds, a few seconds a cell, spent budgets as statuses

FULL_SECONDS = 2
DENSITY_FULL = {f"gen_d{int(100 * d)}": (30, 1000, d, 0.3, 1) for d in (0.15, 0.3, 0.45, 0.6)}
CLASSES_FULL = {"gen_dense": (20, 200, 0.5, 0.2, 1), "gen_normal": (20, 200, 0.33, 0.2, 1), "gen_sparse": (20, 200, 0.18, 0.2, 1)}
ITEMS_FULL = {f"gen_n{n}": (n, 1000, 0.3, 0.3, 1) for n in (10, 20, 40, 80)}
ROWS_FULL = {f"gen_m{m}": (30, m, 0.3, 0.3, 1) for m in (100, 1000, 10_000, 100_000)}
LOW = tuple(round(0.01 * k, 2) for k in range(1, 11))
MIXED = ("order_mix", "doc_words16", "emb_sign8")


def full_grids() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    """Grids without SQL: seconds, searches, conflicts, decisions, backtracks and restarts of every cell, whole GRID rows."""
    at = {"seconds": FULL_SECONDS}
    return {
        "w01_overall_full": lambda s, d: w01_overall(s, d, **at),
        "w02_density_full": lambda s, d: w02_density(s, d, DENSITY_FULL, (0.05, 0.1, 0.2, 0.4, 0.6), **at),
        "w03_low_threshold_full": lambda s, d: run_grid(dbs(s, d, ("emb_sign8", "emb_sign16")), LOW, (BITSET, CP), **at),
        "w04_enumeration_full": lambda s, d: w04_enumeration(s, d, MIXED, (0.2, 0.4, 0.6), **at),
        "w05_search_by_density_full": lambda s, d: w05_search_by_density(s, d, CLASSES_FULL, (0.05,), **at),
        "w06_search_by_threshold_full": lambda s, d: w06_search_by_threshold(s, d, MIXED[:2], THETAS, **at),
        "w08_encodings_full": lambda s, d: w08_encodings(s, d, ("order_mix", "emb_sign8"), (0.02, 0.05, 0.1, 0.2, 0.4, 0.6), **at),
        "w10_profiles_full": lambda s, d: w10_profiles(s, d, thetas=THETAS, **at),
        "w12_items_full": lambda s, d: w12_items(s, d, ITEMS_FULL, (0.1, 0.2, 0.4), **at),
        "w13_rows_full": lambda s, d: w13_rows(s, d, ROWS_FULL, (0.2, 0.4), **at),
        "w14_sweep_full": lambda s, d: w14_sweep(s, d, **at),
        "w16_dual_full": lambda s, d: w16_dual(s, d, MIXED[:2], **at),
        "w17_single_search_full": lambda s, d: w17_single(s, d, ALL, **at),
    }


def _cells(fn: Callable[..., DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    """What is the same on every machine: status and the size of the border."""
    return lambda spark, sf_dir: fn(spark, sf_dir).select("db", "theta", "config", "status", "n_maximal")


def _cells_sql(names, thetas, configs, specs=None) -> str:
    parts = []
    for db in names:
        for t in thetas:
            inner = O.frequent(db, t, generate_sql(*specs[db]), specs[db][1]) if specs else O.frequent(db, t)
            rows = ", ".join(f"('{c}')" for c in configs)
            parts.append(f"select '{db}' as db, {t}::double as theta, config, 'ok' as status, (select count(*) from ({inner} select * from mx)) as n_maximal from (values {rows}) v(config)")
    return "\nunion all\n".join(parts)


def queries() -> dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]]:
    small = ("order_mix", "user_day", "part_attr", "cust_attr", "label_attr")
    search = [c.name for c in SEARCH]
    enum = [f"{s}_{b}" for s in ("optimise", "decide") for b in (B.FULL, B.ITEMS, B.SUBSETS, B.SUBSET)]
    chars = "\nunion all\n".join(f"select '{x}' as db, * from ({O.profile_sql(x)})" for x in ALL if x != "doc_words16")
    return {
        "w01_overall": (_cells(lambda s, d: w01_overall(s, d, small, (0.05, 0.1, 0.2, 0.4))), _cells_sql(small, (0.05, 0.1, 0.2, 0.4), ("native", "jvm", "cp"))),
        "w02_density": (_cells(w02_density), _cells_sql(DENSITY, (0.1, 0.2, 0.4, 0.6), ("bitset", "cp"), DENSITY)),
        "w03_low_threshold": (_cells(w03_low_threshold), _cells_sql(("emb_sign8",), (0.01, 0.02, 0.05, 0.1), ("bitset", "cp"))),
        "w04_enumeration": (_cells(w04_enumeration), _cells_sql(("order_mix",), (0.4, 0.6), enum)),
        "w05_search_by_density": (_cells(w05_search_by_density), _cells_sql(CLASSES, (0.2,), search, CLASSES)),
        "w06_search_by_threshold": (_cells(w06_search_by_threshold), _cells_sql(("order_mix",), (0.2, 0.4), search)),
        "w07_searches_and_times": (w06_search_by_threshold, None),
        "w08_encodings": (_cells(w08_encodings), _cells_sql(("order_mix",), (0.2, 0.4, 0.6), [f"{c}_{r}" for c in ("clausal", "reduced") for r in ("free", "incremental")])),
        "w09_polarity": (_cells(w09_polarity), _cells_sql(("order_mix",), (0.1, 0.2, 0.4, 0.6), ("pos", "neg", "dynamic"))),
        "w10_profiles": (_cells(w10_profiles), _cells_sql(("order_mix",), (0.2, 0.4), ("native", "jvm", "bitset", "cp"))),
        "w11_characteristics": (lambda s, d: w11_characteristics(s, d, [x for x in ALL if x != "doc_words16"]), chars),
        "w12_items": (_cells(w12_items), _cells_sql(ITEMS, (0.1, 0.2), ("cmg", "bitset", "cp"), ITEMS)),
        "w13_rows": (_cells(w13_rows), _cells_sql(ROWS, (0.2, 0.4), ("bitset", "cp"), ROWS)),
        "w14_sweep": (_cells(w14_sweep), _cells_sql(("user_day", "part_attr"), SWEEP, ("bitset", "cp"))),
        "w16_dual": (lambda s, d: w16_dual(s, d).where("config = 'dual'").select("db", "theta", F.col("n_found").alias("n_minimal_infrequent")), "\nunion all\n".join(f"select 'order_mix' as db, {t}::double as theta, (select n_minimal_infrequent from ({O.border_sql('order_mix', t)})) as n_minimal_infrequent" for t in (0.1, 0.15, 0.2, 0.25))),
        "w17_single_search": (lambda s, d: w17_single(s, d).select("db", "theta", "config", "status", (F.col("n_found") > 0).alias("satisfiable")), "\nunion all\n".join(f"select '{x}' as db, {t}::double as theta, config, 'ok' as status, (select count(*) > 0 from ({O.base(x, t)} select * from fi)) as satisfiable from (values ('native'), ('jvm'), ('blackbox')) v(config)" for x in ("order_mix", "user_day", "part_attr", "emb_sign8") for t in (0.1, 0.4))),
        "w18_parameters": (_cells(w_parameters), _cells_sql(("order_mix",), (0.2,), [f"decay_{d}_{b}" for d in (0.8, 0.95) for b in ("items_first", "any")])),
    }
