"""More of the paper's claims as queries: measures, bounds, chances, splitting and sharing, stores on disk, filters in use.

A row (check_name, n, violations, ok) states a claim about chance or space; its bound stands in the query."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from keyless import baselines, codecs, hashing as H, linalg as A, membership as M, perfect as P, sharing, shelf, store as S, thresholds as T
from keyless.shared import scratch
from keyless.trials import key_rows, simulate
from keyless.workloads import QUERIES, SPARSE, SQL, check, check_sql, query, read


def row(spark, name: str, n: int, violations: int) -> DataFrame:
    return spark.createDataFrame([(name, n, violations, violations == 0)], "check_name string, n bigint, violations bigint, ok boolean")


def rows_sql(names: list[str], n: str) -> str:
    return " UNION ALL ".join(check_sql(x, n) for x in names)


# --- splitting and sharing

@query("SELECT c_custkey, c_nationkey AS v FROM customer")
def customer_nation_split(spark, sf_dir):
    df, c = read(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), codecs.offset(0, 5)
    st = sharing.build(df, ["c_custkey"], c.encode(F.col("c_nationkey")), sharing.Plan(width=5))
    st.decode = c.decode
    return sharing.lookup(df.select("c_custkey"), st, out="v")


@query("SELECT c_custkey, c_nationkey AS v FROM customer")
def customer_nation_split_computed(spark, sf_dir):
    """The same without stored tables."""
    df, c = read(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), codecs.offset(0, 5)
    st = sharing.build(df, ["c_custkey"], c.encode(F.col("c_nationkey")), sharing.Plan(width=5))
    st.decode = c.decode
    return sharing.lookup(df.select("c_custkey"), st, out="v", shared=False)


@query(check_sql("shared_tables", "SELECT count(*) FROM customer"))
def shared_table_size(spark, sf_dir):
    """The tables hold two numbers for each function and address, no chunk is above the root of all keys, and addresses close no cycle."""
    df = read(spark, sf_dir, "customer", "c_custkey")
    st = sharing.build(df, ["c_custkey"], F.lit(0), sharing.Plan(width=1))
    bad = (st.table_numbers() != 2 * math.ceil(2 * st.n_keys**0.75) * st.functions) + (st.largest > math.isqrt(st.n_keys)) + (st.chunks < 2 * st.n_keys ** (2 / 3))
    return check(sharing.bits(st), "shared_tables", F.max("n"), F.lit(int(bad)) + F.max((F.col("slot_bits") < F.col("n")).cast("int")))


_FOUR = sharing.fourwise(7)
_CHUNK_SQL = f"(((((({_FOUR[0]}::BIGINT * (k % {H.PRIME}) + {_FOUR[1]}) % {H.PRIME}) * (k % {H.PRIME}) + {_FOUR[2]}) % {H.PRIME}) * (k % {H.PRIME}) + {_FOUR[3]}) % {H.PRIME})"


@query(f"WITH n AS (SELECT count(*) AS n FROM orders), c AS (SELECT {_CHUNK_SQL} % (SELECT ceil(2 * pow(n, 2.0 / 3))::BIGINT FROM n) AS c FROM (SELECT o_orderkey AS k FROM orders)), l AS (SELECT count(*) AS x FROM c GROUP BY c) SELECT max(x)::BIGINT AS largest, (max(x) <= floor(sqrt((SELECT n FROM n))))::BOOLEAN AS ok FROM l")
def chunk_max(spark, sf_dir):
    df = read(spark, sf_dir, "orders", "o_orderkey")
    chunks, limit = T.chunk_plan(df.count())
    return df.groupBy(H.poly_hash(F.col("o_orderkey"), _FOUR, chunks)).count().agg(F.max("count").cast("bigint").alias("largest")).withColumn("ok", F.col("largest") <= limit)


# --- one square system, chances of systems

@query("SELECT doc_id, quality, toxic FROM labels")
def label_lookup_square(spark, sf_dir):
    """As many slots as keys in one system, rows of about twice the logarithm of their number."""
    df = read(spark, sf_dir, "labels")
    width, encode, decode = codecs.pair(codecs.bit(), codecs.bit())
    st = S.build(df, ["doc_id"], encode(F.col("quality"), F.col("toxic")), S.Plan(width=width, kind="square", block=max(df.count(), 1), tries=64), blocks=1)
    a, b = decode(F.col("v"))
    return S.lookup(df.select("doc_id"), st, out="v").select("doc_id", a.alias("quality"), b.alias("toxic"))


#: Systems whose regular share is counted, at least.
_SYSTEMS = 400


def _rate_sql(size: int) -> str:
    return f"(WITH b AS (SELECT greatest(1, count(*) // {size}) AS b FROM orders) SELECT (count(DISTINCT o_orderkey % b) * ceil({_SYSTEMS} / any_value(b)))::BIGINT FROM orders, b)"


@query(" UNION ALL ".join(check_sql(f"regular_{size}", f"SELECT {_rate_sql(size)}") for size in (128, 192, 256)))
def square_success_rate(spark, sf_dir):
    """Square systems of the keys of the orders, dealt to blocks by remainder, each drawn as often as it takes to have enough systems: the
    share of regular ones is within five deviations and the small-size error of .03 of the constant."""
    df, out = read(spark, sf_dir, "orders", "o_orderkey"), None
    total, parts = df.count(), int(spark.conf.get("spark.sql.shuffle.partitions"))
    for size in (128, 192, 256):
        blocks = max(1, total // size)
        trials = math.ceil(_SYSTEMS / blocks)

        def run(batches, plan=S.Plan(width=1, kind="square", block=size, tries=1)):
            good = [found[2] == S.GOOD for _, _, found in S.solved(lambda some: S.solve_blocks(plan, some), batches)]
            yield pa.RecordBatch.from_pydict({"n": [len(good)], "good": [sum(good)]})

        drawn = H.digests(df, ["o_orderkey"]).select((F.pmod("o_orderkey", F.lit(blocks)) * trials).alias("block"), "d1", "d2", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))).alias("t"))
        own = [F.xxhash64(F.col("t").cast("bigint"), c).alias(c) for c in ("d1", "d2")]
        rows = drawn.select((F.col("block") + F.col("t")).alias("block"), *own, F.lit(0).cast("bigint").alias("value")).repartition(min(parts, blocks * trials), "block").sortWithinPartitions("block", "d1", "d2")
        got = rows.mapInArrow(run, "n long, good long").agg(F.sum("n").alias("n"), F.sum("good").alias("good"))
        bound = 5 * F.sqrt(F.lit(T.SQUARE_SUCCESS * (1 - T.SQUARE_SUCCESS)) / F.col("n")) + 0.03
        one = check(got, f"regular_{size}", F.max("n"), F.max((F.abs(F.col("good") / F.col("n") - T.SQUARE_SUCCESS) > bound).cast("int")))
        out = one if out is None else out.unionAll(one)
    return out


def shares(d1: np.ndarray, d2: np.ndarray, n: int, load: float, k: int, kind: str, trials: int) -> tuple[float, float, float]:
    """Shares of systems of n of the keys with full rank, with an order of peeling, and with a placement."""
    m, got = round(n / load), np.zeros(3)
    for t in range(trials):
        rows = key_rows(d1[:n], d2[:n], m, k, kind, 7919 * t + k)
        got += (A.rank2(rows) == n, kind == "distinct" and A.peel_order(rows, m) is not None, A.match(rows) is not None)
    return tuple(float(x) for x in got / trials)


def _curve(name: str, kind: str, ks: tuple[int, ...], loads, n: int = 1000, trials: int = 10):
    def run(spark, sf_dir):
        grid = [(k, round(x, 4), n) for k in ks for x in loads(k)]
        return simulate(read(spark, sf_dir, "orders", "o_orderkey"), n, grid, "k long, load double, n long", lambda d1, d2, k, load, n: shares(d1, d2, n, load, k, kind, trials), "rank double, peel double, place double")

    run.__name__ = name
    QUERIES[name] = run


_curve("rank_success_curve", "distinct", (3, 4), lambda k: [T.theta(k) + d for d in (-0.06, -0.03, 0.0, 0.03)])
_curve("peel_threshold_curve", "distinct", (3, 4), lambda k: [1 / T.PEEL_RATIO[k] + d for d in (-0.08, -0.04, 0.0, 0.04, 0.08)])
_curve("kary_vs_rank_threshold", "distinct", (3, 4), lambda k: [T.theta(k) + d for d in (-0.04, 0.01, 0.04)])
_curve("two_run_rank_rate", "two_runs", (16,), lambda k: [0.8, 0.88, 0.94, 0.98])


@query(rows_sql(["rank_below", "rank_above", "peel_below", "peel_above", "rank_is_placed", "peel_is_rank"], "6"))
def threshold_sides(spark, sf_dir):
    """Almost all systems are good well below a threshold and almost none well above; what peels has full rank, and that has a placement."""
    grid = [(k, where, n) for k in (3, 4) for where in ("rank-", "rank+", "peel-", "peel+") for n in (600, 1000, 1400)]

    def run(d1, d2, k, where, n):
        middle = T.theta(k) if where.startswith("rank") else 1 / T.PEEL_RATIO[k]
        return shares(d1, d2, n, middle + (0.05 if where.endswith("+") else -0.05), k, "distinct", 8)

    got = simulate(read(spark, sf_dir, "orders", "o_orderkey"), 1400, grid, "k long, side string, n long", run, "rank double, peel double, place double")
    at = lambda side, bad: F.count_if((F.col("side") == side) & bad)
    checks = {
        "rank_below": at("rank-", F.col("rank") < 0.75), "rank_above": at("rank+", F.col("rank") > 0.25), "peel_below": at("peel-", F.col("peel") < 0.75), "peel_above": at("peel+", F.col("peel") > 0.25),
        "rank_is_placed": F.greatest(F.count_if(F.col("place") < F.col("rank")), F.lit(0)), "peel_is_rank": F.count_if(F.col("rank") < F.col("peel")),
    }
    one = got.agg(*[v.cast("bigint").alias(k) for k, v in checks.items()]).unpivot([], list(checks), "check_name", "violations")
    return one.select("check_name", F.lit(6).cast("bigint").alias("n"), "violations", (F.col("violations") == 0).alias("ok"))


@query(check_sql("row_weights", "SELECT count(*) FROM orders"))
def row_weight_histogram(spark, sf_dir):
    """Weights by the tabulated distribution stay inside the clip; their mean is that of the clipped law within five deviations."""
    n = 1 << 16
    lo, cuts = H.weight_cuts(n)
    d = H.digests(read(spark, sf_dir, "orders", "o_orderkey"), ["o_orderkey"]).withColumn("u", H.draw(H.WEIGHT, 1, 0, 2**62))
    weight = F.lit(lo) + sum((F.col("u") >= F.lit(int(c))).cast("int") for c in cuts)
    mass = np.diff(np.concatenate([[0.0], cuts / 2.0**62, [1.0]]))
    mean = float((mass * np.arange(lo, lo + len(mass))).sum())
    spread = float(np.sqrt((mass * (np.arange(lo, lo + len(mass)) - mean) ** 2).sum()))
    got = d.select(weight.alias("w"))
    bad = F.count_if((F.col("w") < math.ceil(0.5 * math.log(n))) | (F.col("w") > 4 * math.log(n))) + (F.abs(F.avg("w") - mean) > 5 * spread / F.sqrt(F.count("*"))).cast("int")
    return check(got, "row_weights", F.count("*"), bad)


# --- space

_PLANS = {"sparse": SPARSE, "compressed": S.Plan(compressed=True), "square": S.Plan(kind="square", block=128, tries=64), "peel": S.Plan(kind="peel", k=3, slack=0.23, block=4096, tries=32)}
#: Slot bits by the width, and side bits a key, at most.
_SPACE = {"sparse": (1.10, 0.2), "compressed": (1.45, 0.2), "square": (1.0, 0.4), "peel": (1.33, 0.1)}


@query(rows_sql(sorted(_PLANS), "SELECT count(*) FROM orders"))
def store_space_bounds(spark, sf_dir):
    """No store is below the values themselves, and none above its own formula."""
    df, out = read(spark, sf_dir, "orders", "o_orderkey"), None
    for name, plan in _PLANS.items():
        st = S.build(df, ["o_orderkey"], F.col("o_orderkey") % 256, S.replace(plan, width=8))
        factor, side = _SPACE[name]
        bad = (F.col("slot_bits") < 8 * F.col("n")).cast("int") + (F.col("slot_bits") > factor * 8 * F.col("n") + 4096).cast("int") + (F.col("side_bits") > side * F.col("n") + 4096).cast("int") + F.lit(int(S.stored_bits(st) < 8 * st.n_keys))
        one = check(S.logical_bits(st), name, F.max("n"), F.max(bad))
        out = one if out is None else out.unionAll(one)
    return out


@query()
def store_measures(spark, sf_dir):
    """(kind, n, logical_bits, stored_bits, factor, excess_bits, slots_read, adaptive) of each method, values of 8 bits."""
    df, out = read(spark, sf_dir, "orders", "o_orderkey"), []
    for name, plan in {**_PLANS, "overflow": S.Plan(block=64, headroom=0.25, tries=1), "compensated": S.Plan(block=64, headroom=0.25, tries=1, combine="compensate", equal_segments=True)}.items():
        st = S.build(df, ["o_orderkey"], F.col("o_orderkey") % 256, S.replace(plan, width=8))
        b = S.logical_bits(st).first()
        total, least = b["slot_bits"] + b["side_bits"], T.retrieval_lower_bound(b["n"], 8)
        out.append((name, b["n"], total, S.stored_bits(st), total / max(least, 1), total - least, *S.reads(st)))
    return spark.createDataFrame(out, "kind string, n long, logical_bits long, stored_bits long, factor double, excess_bits long, slots_read int, adaptive boolean")


@query(rows_sql(["sparse", "compressed", "square", "peel", "bloom"], "SELECT count(*) FROM events WHERE event_id % 2 = 0"))
def lower_bound_check(spark, sf_dir):
    """No filter with 6 signature bits takes fewer bits than any filter must."""
    ev, out = read(spark, sf_dir, "events", "event_id").filter("event_id % 2 = 0"), None
    for name, plan in _PLANS.items():
        flt = M.build_filter(ev, ["event_id"], 6, plan)
        one = check(S.logical_bits(flt), name, F.max("n"), F.max((F.col("slot_bits") < math.floor(T.filter_lower_bound(flt.n_keys, 2.0**-6, 2.0**63))).cast("int")))
        out = one if out is None else out.unionAll(one)
    n = ev.count()
    return out.unionAll(row(spark, "bloom", n, int(baselines.bloom_bits(n, 2.0**-6)[0] < T.filter_lower_bound(n, 2.0**-6, 2.0**63))))


@query(rows_sql(["perfect", "minimal"], "SELECT count(*) FROM part"))
def perfect_hash_bits(spark, sf_dir):
    """Two bits a slot with four choices; the slots without a key are few enough that the minimal form stays below 2.7 bits a key."""
    df, out = read(spark, sf_dir, "part", "p_partkey"), None
    for name, minimal in (("perfect", False), ("minimal", True)):
        ph = P.build_perfect(df, ["p_partkey"], slack=0.05, block=512, minimal=minimal)
        n = F.col("n")
        bad = (F.col("choice_bits") + F.col("rank_bits") > (2.7 if minimal else 2.15) * n + 64).cast("int") + (F.col("choice_bits") < 2 * n).cast("int")
        one = check(P.hash_bits(ph), name, F.max("n"), F.max(bad))
        out = one if out is None else out.unionAll(one)
    return out


_GAP = f"(({baselines.COEFFICIENTS[0][0]}::BIGINT * (p_partkey % {H.PRIME}) + {baselines.COEFFICIENTS[0][1]}) % {H.PRIME}) % (SELECT count(*) * 64 FROM part)"


@query(f"WITH s AS (SELECT count(*) * 64 AS u FROM part), h AS (SELECT DISTINCT {_GAP} AS h FROM part), r AS (SELECT h, floor(h * 64 / u)::BIGINT AS r, u FROM h, s), g AS (SELECT h - coalesce(lag(h) OVER (PARTITION BY r ORDER BY h), floor(r * u / 64)::BIGINT) AS g FROM r) SELECT count(*)::BIGINT AS n, sum(floor(g / 64) + 7)::BIGINT AS bits FROM g")
def gap_code_bits(spark, sf_dir):
    """Sending the sorted hashes as gaps, for a rate of one in 64."""
    df = read(spark, sf_dir, "part", "p_partkey")
    return baselines.gap_bits(df, "p_partkey", 64 * df.count())


# --- overflow

def _load(size: str) -> str:
    a, b = baselines.COEFFICIENTS[3]
    return f"(({a}::BIGINT * (o_orderkey % {H.PRIME}) + {b}) % {H.PRIME}) % (SELECT ceil(count(*) / {size}.0)::BIGINT FROM orders)"


@query(" UNION ALL ".join(f"SELECT {b}::INTEGER AS block, coalesce(sum(x), 0)::BIGINT AS keys FROM (SELECT count(*) AS x FROM (SELECT {_load(str(b))} AS b FROM orders) GROUP BY b HAVING count(*) > 1.25 * {b})" for b in (32, 64, 128, 256)))
def oversize_overflow(spark, sf_dir):
    """Keys of blocks above the cap, by the mean size of a block."""
    df, out = read(spark, sf_dir, "orders", "o_orderkey"), None
    n = df.count()
    for b in (32, 64, 128, 256):
        loads = df.groupBy(H.poly_hash(F.col("o_orderkey"), baselines.COEFFICIENTS[3], max(1, -(-n // b)))).count()
        one = loads.filter(F.col("count") > 1.25 * b).agg(F.coalesce(F.sum("count"), F.lit(0)).cast("bigint").alias("keys")).select(F.lit(b).alias("block"), "keys")
        out = one if out is None else out.unionAll(one)
    return out


@query()
def overflow_by_reason(spark, sf_dir):
    """(block, reason, share): oversize blocks are never tried, dependent ones have used up their tries."""
    df, out = read(spark, sf_dir, "orders", "o_orderkey"), None
    reason = F.when(F.col("status") == S.GOOD, "none").when(F.col("seed") == 0, "oversize").otherwise("dependent")
    for block in (32, 64, 128, 256):
        seg = S.build(df, ["o_orderkey"], F.lit(0), S.Plan(width=1, block=block, headroom=0.25, tries=1)).segments
        total = seg.agg(F.sum("n_keys").alias("total"))
        one = seg.groupBy(reason.alias("reason")).agg(F.sum("n_keys").alias("n")).join(F.broadcast(total)).select(F.lit(block).alias("block"), "reason", (F.col("n") / F.col("total")).alias("share"))  # one row
        out = one if out is None else out.unionAll(one)
    return out


@query("SELECT event_id, event_type AS v FROM events")
def event_type_long_form_overflow(spark, sf_dir):
    """The lookup by relations where many blocks are given up."""
    df = read(spark, sf_dir, "events", "event_id", "event_type")
    c = codecs.dictionary(df, "event_type")
    st = S.build(df, ["event_id"], c.encode(F.col("event_type")), S.Plan(width=c.width, block=64, headroom=0.05, tries=1))
    return S.lookup_long(df, st, "event_id", "raw").select("event_id", c.decode(F.col("raw")).alias("v"))


@query(check_sql("flat", "SELECT count(*) FROM orders"))
def flat_store_equals_two_tables(spark, sf_dir):
    """Both tables behind one another as one array, and one rule: the slots of a key in both are summed."""
    df = read(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    plan = S.Plan(width=4, block=64, headroom=0.25, tries=1, combine="compensate", equal_segments=True)
    st = S.build(df, ["o_orderkey"], F.pmod("o_custkey", F.lit(16)), plan)
    flat, cells = S.flatten(st), S.flat_slots(H.digests(df, ["o_orderkey"]).select("o_orderkey", "d1", "d2"), st)
    one = cells.join(flat, "pos").groupBy("o_orderkey").agg(F.bit_xor("val").alias("a"))
    got = S.lookup(df, st, out="b").join(one, "o_orderkey", "left")
    return check(got, "flat", F.count("*"), F.count_if(F.coalesce("a", F.lit(0)) != F.col("b")))


# --- filters

_FAMILIES = ["mixed", "pairwise", "fourwise"]


@query(rows_sql(_FAMILIES, "SELECT count(*) FROM events WHERE event_id % 2 = 1"))
def hash_family_ablation(spark, sf_dir):
    """Signatures of 6 bits by simple families: no member is missed, and strangers pass within the bound and the loss of a simple family."""
    ev, out = read(spark, sf_dir, "events", "event_id"), None
    for name in _FAMILIES:
        sign = {"mixed": lambda d: H.draw(H.SIGNATURE, 1, 0, 64), "pairwise": lambda d: H.poly_hash(d, sharing.fourwise(3)[:2], 64), "fourwise": lambda d: H.poly_hash(d, sharing.fourwise(3), 64)}[name]
        signed = H.digests(ev, ["event_id"]).withColumn("sig", sign(F.col("d1")))
        st = S.build(signed.filter("event_id % 2 = 0").select("event_id", "sig"), ["event_id"], F.col("sig"), S.Plan(width=6))
        got = S.lookup(signed.select("event_id", "sig"), st, out="got")
        hit, odd = F.col("got") == F.col("sig"), F.col("event_id") % 2 == 1
        loss = 1 / math.sqrt(max(st.n_keys, 1))
        n = F.count_if(odd)
        p = 2.0**-6
        one = check(got, name, n, F.count_if(~odd & ~hit) + (F.count_if(odd & hit) > n * (p + loss) + 5 * F.sqrt(n * p) + 1).cast("int"))
        out = one if out is None else out.unionAll(one)
    return out


@query("SELECT o_orderkey, o_orderpriority AS v FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)")
def guarded_peel_members(spark, sf_dir):
    df = read(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority").join(read(spark, sf_dir, "lineitem", "l_orderkey").distinct(), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi")
    c = codecs.dictionary(df, "o_orderpriority")
    st = M.build_guarded(df, ["o_orderkey"], c.encode(F.col("o_orderpriority")), c.width, 8, S.Plan(kind="peel", k=3, slack=0.25, block=4096, tries=32))
    st.decode = c.decode
    return M.guarded(df.select("o_orderkey"), st, out="v")


@query()
def filter_rates(spark, sf_dir):
    """(s, n, hits, rate, expected): what was measured, beside what is expected."""
    ev, out = read(spark, sf_dir, "events", "event_id"), None
    for s in (4, 7, 10):
        got = M.maybe(ev.filter("event_id % 2 = 1"), M.build_filter(ev.filter("event_id % 2 = 0"), ["event_id"], s))
        one = got.agg(F.lit(s).alias("s"), F.count("*").alias("n"), F.count_if("maybe").alias("hits"), F.avg(F.col("maybe").cast("int")).alias("rate"), F.lit(2.0**-s).alias("expected"))
        out = one if out is None else out.unionAll(one)
    return out


_SHINGLES = "list_distinct([array_to_string(w[i:i+7], ' ') FOR i IN range(1, len(w) - 6)])"


@query(f"WITH b AS (SELECT DISTINCT unnest({_SHINGLES}) AS g FROM (SELECT str_split(text, ' ') AS w FROM benchmark WHERE text IS NOT NULL)), d AS (SELECT doc_id, unnest({_SHINGLES}) AS g FROM (SELECT doc_id, str_split(text, ' ') AS w FROM documents WHERE text IS NOT NULL)) SELECT doc_id, count(*)::BIGINT AS hits FROM d WHERE g IN (SELECT g FROM b) GROUP BY doc_id")
def benchmark_leak_filter(spark, sf_dir):
    """Documents that share eight words in a row with the benchmark: the filter first, what passes is compared exactly."""

    def grams(df: DataFrame, *keep: str) -> DataFrame:
        w = df.filter("text is not null").select(*keep, F.split("text", " ", -1).alias("w")).filter(F.size("w") >= 8)
        return w.select(*keep, F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 7), lambda i: F.array_join(F.slice("w", i, 8), " ")))).alias("g"))

    wanted = grams(read(spark, sf_dir, "benchmark", "text")).distinct()
    seen = M.maybe(grams(read(spark, sf_dir, "documents", "doc_id", "text"), "doc_id"), M.build_filter(wanted, ["g"], 10)).filter("maybe").drop("maybe")
    return seen.join(wanted, "g", "left_semi").groupBy("doc_id").agg(F.count("*").alias("hits"))


@query("WITH d AS (SELECT (o_orderdate::DATE - DATE '1970-01-01')::BIGINT AS d FROM orders), r AS (SELECT unnest(range((SELECT min(d) FROM d) - 30, (SELECT max(d) FROM d) + 30, 5)) AS lo) SELECT lo, count(d)::BIGINT AS n FROM r LEFT JOIN d ON d >= lo AND d < lo + 3 GROUP BY lo HAVING count(d) > 0")
def range_emptiness(spark, sf_dir):
    """Three days from every fifth day on, by at most three dyadic pieces each; ranges that may hold something are counted exactly."""
    days = read(spark, sf_dir, "orders", "o_orderdate").select(F.unix_date(F.col("o_orderdate").cast("date")).cast("bigint").alias("d"))
    levels = [F.struct(F.lit(j).cast("bigint").alias("level"), F.floor(F.col("d") / 2**j).alias("piece")) for j in (0, 1)]
    flt = M.build_filter(days.distinct().select(F.explode(F.array(*levels)).alias("x")).select("x.*"), ["level", "piece"], 8)
    ends = days.agg(F.min("d").alias("a"), F.max("d").alias("b"))
    ranges = ends.filter("a is not null").select(F.explode(F.sequence(F.col("a") - 30, F.col("b") + 29, F.lit(5).cast("bigint"))).alias("lo"))
    even = F.struct(F.lit(1).cast("bigint").alias("level"), F.floor((F.col("lo") + F.col("lo") % 2) / 2).alias("piece"))
    single = F.struct(F.lit(0).cast("bigint").alias("level"), F.when(F.col("lo") % 2 == 0, F.col("lo") + 2).otherwise(F.col("lo")).alias("piece"))
    hits = M.maybe(ranges.select("lo", F.explode(F.array(even, single)).alias("x")).select("lo", "x.*"), flt).groupBy("lo").agg(F.bool_or("maybe").alias("maybe")).filter("maybe")
    # the days of a range meet the days of the table, so no range is compared with every day
    each = hits.select("lo", F.explode(F.sequence(F.col("lo"), F.col("lo") + 2)).alias("d"))
    return each.join(days.groupBy("d").agg(F.count("*").alias("x")), "d").groupBy("lo").agg(F.sum("x").cast("bigint").alias("n"))


@query("SELECT host, count(*)::BIGINT AS pages FROM (SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host FROM pages) WHERE host IN (SELECT regexp_extract(url, '^https?://([^/]+)', 1) FROM pages WHERE page_id % 2 = 0) GROUP BY host")
def page_host_filter(spark, sf_dir):
    """Pages whose host has a page of even number, the filter before the exact semi-join."""
    host = F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host")
    pages = read(spark, sf_dir, "pages", "page_id", "url")
    wanted = pages.filter("page_id % 2 = 0").select(host).distinct()
    return M.maybe(pages.select(host), M.build_filter(wanted, ["host"], 8)).filter("maybe").join(wanted, "host", "left_semi").groupBy("host").agg(F.count("*").alias("pages"))


@query("SELECT n_name, count(*)::BIGINT AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE c_mktsegment = 'BUILDING' GROUP BY 1")
def star_prefilter(spark, sf_dir):
    dim = read(spark, sf_dir, "customer").filter("c_mktsegment = 'BUILDING'").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey")
    fact = M.prefilter_join(read(spark, sf_dir, "orders", "o_custkey"), dim, "o_custkey", M.build_filter(dim, ["o_custkey"], 8))
    return fact.join(read(spark, sf_dir, "nation", "n_nationkey", "n_name"), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


# --- stores on disk

def _shelved(spark, sf_dir, name: str) -> tuple[DataFrame, str, codecs.Codec]:
    df = read(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority")
    c, path = codecs.dictionary(df, "o_orderpriority"), scratch(spark, name)
    shelf.write(S.build(df, ["o_orderkey"], c.encode(F.col("o_orderpriority")), S.Plan(width=c.width, block=64, headroom=0.25, tries=1)), path, 0, per_range=16)
    return df, path, c


@query("SELECT o_orderkey, o_orderpriority AS v FROM orders")
def store_write_read(spark, sf_dir):
    df, path, c = _shelved(spark, sf_dir, "shelf")
    return S.lookup(df.select("o_orderkey"), shelf.read(spark, path, decode=c.decode), out="v")


@query(check_sql("scan", "SELECT count(*) FROM orders"))
def store_scan(spark, sf_dir):
    """Ranges of blocks, read apart, are all blocks."""
    df, path, _ = _shelved(spark, sf_dir, "scan")
    parts = shelf.scan(spark, path, 0, last=15, per_range=16).unionAll(shelf.scan(spark, path, 0, first=16, per_range=16))
    n = df.count()
    return check(parts, "scan", F.sum("n_keys"), F.abs(F.sum("n_keys") - n) + F.count("*") - F.count_distinct("block"))


@query("SELECT o_orderkey, CASE WHEN o_orderkey % 2 = 0 THEN 1 ELSE 2 END::BIGINT AS v FROM orders")
def store_epochs(spark, sf_dir):
    """A rebuild is a new epoch, and readers take the latest."""
    df, path = read(spark, sf_dir, "orders", "o_orderkey"), scratch(spark, "epochs")
    shelf.write(S.build(df, ["o_orderkey"], F.lit(0), S.Plan(width=2)), path, 0)
    shelf.write(S.build(df, ["o_orderkey"], F.col("o_orderkey") % 2 + 1, S.Plan(width=2)), path, 1)
    return S.lookup(df, shelf.read(spark, path), out="v")


assert set(SQL) <= set(QUERIES)
