"""Registered measures: reads by span length, bounds beside counts, open shares by level, rates over tolerances."""

from __future__ import annotations

from math import log2

from pyspark.sql import Window
from pyspark.sql import functions as F

from . import oracles as sql
from .functions.typeindex import TypicalSet
from .operators import baselines, ladder
from .operators.blocks import settled, symbol_count
from .plans import bounds
from .plans.schedules import PRESETS, block_length, ladder_schedule, paper_levels
from .queries import STRETCH, _blocks, _saved_store, _store
from .sources.catalog import law_of, symbol_column

SPANS = (1, 2, 3, 64, 128, 200, 512, 2048)


def read_measures(spark, sf_dir):
    """Probes of reads of s symbols over all starts, by length.

    A start's reads touch one number of blocks or one more, by its offset; ``inside`` and ``across`` sum the probes of
    both kinds over the first blocks of spans, so ``across / blocks`` is the greatest mean of any start and ``worst``
    the worst read.  ``sublinear``: s symbols at once cost less than s single reads.
    """
    st = _saved_store(spark, sf_dir)
    s, b0 = st.schedule, st.schedule.b0
    units, most = max(st.n // b0, 1), (max(SPANS) - 1) // b0 + 2
    costs = st.table("blocks").select("blk", ladder.full_cost(s, F.col("home")).alias("c"))
    own = F.floor(F.col("blk") / STRETCH)
    dealt = costs.select("*", F.explode(F.array_distinct(F.array(own, F.floor(F.greatest(F.col("blk") - most + 1, F.lit(0)) / STRETCH)))).alias("stretch"))
    ahead = lambda m: F.sum("c").over(Window.partitionBy("stretch").orderBy("blk").rowsBetween(0, m - 1))
    out = None
    for length in SPANS:
        q, r = divmod(length - 1, b0)
        per = dealt.select("blk", "stretch", ahead(q + 1).alias("low"), ahead(q + 2 if r else q + 1).alias("high")).where((F.floor(F.col("blk") / STRETCH) == F.col("stretch")) & (F.col("blk") + q + 2 <= units - 1))
        one = per.agg(F.count("*").alias("blocks"), F.sum("low").alias("inside"), F.sum("high").alias("across"), F.max("high").alias("worst")).select(F.lit(length).cast("long").alias("span"), "*")
        out = one if out is None else out.unionByName(one)
    single = out.where("span = 1").select(F.col("across").alias("single"), F.col("blocks").alias("of"))
    return out.join(F.broadcast(single)).select("span", "blocks", "inside", "across", "worst", (F.col("across") * F.col("of") < F.col("span") * F.col("single") * F.col("blocks")).alias("sublinear"))


def bounds_check(spark, sf_dir):
    """Sum of all single reads against twice, and of edits against eight times, the base block (or its word, if wider)."""
    out = None
    for preset in ("demo3", "calm", "flag3"):
        st = _store(spark, sf_dir, preset)
        limit = 2 * max(st.schedule.b0, st.schedule.k0)
        one = st.state.agg(F.sum(F.col("n_sym") * ladder.full_cost(st.schedule, F.col("home"))).alias("probes"), F.sum("n_sym").alias("n")).select(F.lit(preset).alias("preset"), F.lit("read").alias("what"), "probes", "n", F.lit(limit).cast("long").alias("limit"))
        out = one if out is None else out.unionByName(one)
    from .queries import ladder_update_cost

    st = _saved_store(spark, sf_dir)
    edits = ladder_update_cost(spark, sf_dir).agg(F.sum(F.col("bits_read") + F.col("bits_written")).alias("probes"), F.count("*").alias("n"))
    out = out.unionByName(edits.select(F.lit("demo3").alias("preset"), F.lit("edit").alias("what"), "probes", "n", F.lit(8 * max(st.schedule.b0, st.schedule.k0)).cast("long").alias("limit")))
    return out.select("*", (F.col("probes") <= F.col("n") * F.col("limit")).alias("holds"))


def open_profile(spark, sf_dir):
    """Open units by level, and open units whose group is open too (the conditional share), beside the bound's exponent."""
    st = _store(spark, sf_dir, "deep3")
    s, beta = st.schedule, 3 * 0.5 * st.schedule.b0
    out, below, name = None, st.state.select("blk", "settled", "g1", "settled1"), "blk"
    for i in range(len(s.levels)):
        units = below.agg(F.count("*").alias("units"), F.sum((~F.col("settled")).cast("long")).alias("open_units"), F.sum((~F.col("settled") & ~F.col(f"settled{i + 1}")).cast("long")).alias("open_in_open"))
        exponent = round(beta * 2**i * log2(0.5 / 2**i), 6)
        one = units.select(F.lit(i).alias("level"), "units", "open_units", "open_in_open", F.lit(exponent).alias("log_bound"))
        out = one if out is None else out.unionByName(one)
        if i + 1 < len(s.levels):
            below = st.state.select(f"g{i + 1}", F.col(f"settled{i + 1}").alias("settled"), f"settled{i + 2}").distinct()
    return out


def residual_entropy(spark, sf_dir):
    """Symbols that are still carried above each level, and the entropy per position of markers and symbols mixed."""
    st = _store(spark, sf_dir)
    law, out = st.law, None
    for i in range(len(st.schedule.levels) + 1):
        carried = F.coalesce("home", F.lit(99)) > i
        counts = st.state.agg(F.sum("n_sym").alias("n"), *[F.coalesce(F.sum(F.when(carried, symbol_count(F.col("body"), c).cast("long"))), F.lit(0)).alias(f"c{j}") for j, c in enumerate(law.chars)])
        total = sum((F.col(f"c{j}") for j in range(law.k)), F.lit(0))
        shares = [total * 0 + F.col("n") - total, *[F.col(f"c{j}") for j in range(law.k)]]
        h = sum((F.when(x > 0, -x / F.col("n") * F.log2(x / F.col("n"))).otherwise(0.0) for x in shares), F.lit(0.0))
        one = counts.select(F.lit(i).alias("level"), total.cast("long").alias("carried"), F.round(h, 6).alias("entropy"))
        out = one if out is None else out.unionByName(one)
    return out


RATES = ((2, 512), (4, 2048), (8, 8192), (16, 32768), (32, 131072))


def rate_curve(spark, sf_dir):
    """Reserved bits a symbol of flat blocks and of the ladder as the tolerance 1/d shrinks, beside entropy, bound and raw width."""
    law = law_of(symbol_column(spark, sf_dir, "li_zero_tax"))
    rows = []
    for d, b0 in RATES:
        k0 = -(-(law.entropy + 1 / d) * b0 // 1)
        level = (16 * d + 16 * d // (2 * d) * b0 * 2) / (16 * d * b0)
        rows.append((d, b0, round(law.entropy, 6), round(k0 / b0, 6), round(k0 / b0 + level, 6), round(bounds.rate_bound(law, 1 / d), 6), k0 / b0 + level < 1))
    return spark.createDataFrame(rows, "inverse_eps long, b0 long, entropy double, flat double, ladder double, bound double, below_raw boolean")


def entropy_gap_check(spark, sf_dir):
    """Greatest distance of a settled block's entropy from the law's, beside the bound for laws that close."""
    blocks, law, s, _ = _blocks(spark, sf_dir, "flag3")
    n = F.length("body")
    share = [symbol_count(F.col("body"), c) / n for c in law.chars]
    h = sum((F.when(p > 0, -p * F.log2(p)).otherwise(0.0) for p in share), F.lit(0.0))
    gap = blocks.where(settled(F.col("body"), law, s.num, s.den)).agg(F.count("*").alias("blocks"), F.max(F.abs(h - law.entropy)).alias("gap"))
    return gap.select("blocks", F.round("gap", 6).alias("gap"), F.lit(round(bounds.entropy_gap(law, 0.5), 6)).alias("bound"), (F.col("gap") <= bounds.entropy_gap(law, 0.5)).alias("holds"))


def flat_error_bound(spark, sf_dir):
    """Failed flat blocks against the union bound over blocks of the exact open probability."""
    blocks, law, s, n = _blocks(spark, sf_dir, "demo3")
    t = TypicalSet(list(law.counts), s.num, s.den, s.b0)
    from math import comb

    p = law.counts[1] / law.total
    inside = sum(comb(s.b0, w) * p**w * (1 - p) ** (s.b0 - w) for w in range(t.bounds[1][0], t.bounds[1][1] + 1))
    failed = baselines.flat(blocks, law, s).agg(F.sum(F.col("failed").cast("long")).alias("failed"))
    return failed.select("failed", F.lit(round(1 - inside, 6)).alias("open_probability"), F.lit(round(min(1.0, n / s.b0 * (1 - inside)), 6)).alias("error_bound"))


def reader_orders(spark, sf_dir):
    """What the analytic baselines promise, and the lengths that the published schedule asks for, over tolerances."""
    law = law_of(symbol_column(spark, sf_dir, "li_small_qty"))
    n, rows = law.total, []
    for d in (4, 8, 16, 32):
        two, b0 = bounds.two_level_cost(n, 1 / d), block_length(law, 1 / d)
        rows.append((d, round(two["read"], 6), round(two["update"], 6), round(bounds.single_read_floor(1 / d), 6), b0, paper_levels(10**14, b0), round(bounds.home_bound(1 / d, 1, 3 * b0 / d), 6), round(bounds.zero_error_rate(n, law.entropy + 1 / d, 0.0, law.k), 6), round(bounds.lz_slack(law, 1 / d, b0, 1.0), 6), round(bounds.lz_bound(law.entropy, 512, 1, 1.0), 6), bounds.flat_error(n, b0, 1 / d) < 1))
    return spark.createDataFrame(rows, "inverse_eps long, two_level_read double, two_level_update double, read_floor double, block_length long, levels_at_1e14 long, home1_bound double, zero_error_rate double, lz_slack double, lz_bound_512 double, flat_safe boolean")


QUERIES = {f.__name__: f for f in (read_measures, bounds_check, open_profile, residual_entropy, rate_curve, entropy_gap_check, flat_error_bound, reader_orders)}

_full = sql._FULL.format(h="home")
_reads = " UNION ALL ".join(f"SELECT CAST({k} AS BIGINT) AS span, count(*) AS blocks, CAST(sum(low) AS BIGINT) AS inside, CAST(sum(high) AS BIGINT) AS across, CAST(max(high) AS BIGINT) AS worst FROM (SELECT blk, sum(c) OVER (ORDER BY blk ROWS BETWEEN CURRENT ROW AND {(k - 1) // 128} FOLLOWING) AS low, sum(c) OVER (ORDER BY blk ROWS BETWEEN CURRENT ROW AND {(k - 1) // 128 + ((k - 1) % 128 > 0)} FOLLOWING) AS high FROM cost), nn WHERE blk + {(k - 1) // 128 + 2} <= n // 128 - 1" for k in SPANS)
_rd = " UNION ALL ".join(f"SELECT '{p}' AS preset, 'read' AS what, * FROM ({sql._demo(sql._widths(b0, k=k), source=src, b0=b0)} SELECT CAST(sum(n_sym * {_full}) AS BIGINT) AS probes, CAST(sum(n_sym) AS BIGINT) AS n, CAST(2 * max(greatest({b0}, k0)) AS BIGINT) AS lim FROM home, kk)" for p, src, b0, k in (("demo3", "li_small_qty", 128, 2), ("calm", "li_zero_tax", 256, 2), ("flag3", "li_flag", 32, 3)))
_x = lambda c: f"CASE WHEN {c} > 0 THEN -{c} / CAST(n AS DOUBLE) * log2({c} / CAST(n AS DOUBLE)) ELSE 0 END"
_cc = "(length(body) - length(replace(body, '{}', '')))"
_h = "-sum(CAST(c AS DOUBLE) / n * log2(CAST(c AS DOUBLE) / n))"
ORACLES = {
    "read_measures": sql._demo(sql._widths(128), f"cost AS (SELECT blk, {_full} AS c FROM home, kk)", f"m AS ({_reads})") + "SELECT m.*, m.across * o.blocks < m.span * o.across * m.blocks AS sublinear FROM m, (SELECT * FROM m WHERE span = 1) o",
    "bounds_check": f"""SELECT preset, what, probes, n, lim AS "limit", probes <= n * lim AS holds FROM ({_rd} UNION ALL SELECT 'demo3', 'edit', * FROM ({sql._cost} SELECT CAST(sum(bits_read + bits_written) AS BIGINT), count(*), CAST(8 * max(greatest(128, k0)) AS BIGINT) FROM costs, kk))""",
    "open_profile": sql._demo(b0=64) + """SELECT CAST(0 AS INTEGER) AS level, count(*) AS units, count(*) FILTER (NOT settled) AS open_units, count(*) FILTER (NOT settled AND NOT s1) AS open_in_open, round(CAST(-96 AS DOUBLE), 6) AS log_bound FROM home
UNION ALL SELECT 1, count(*), count(*) FILTER (NOT l1.settled), count(*) FILTER (NOT l1.settled AND NOT l2.settled), CAST(-384 AS DOUBLE) FROM l1 JOIN l2 USING (g2)""",
    "residual_entropy": sql._demo() + " UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS level, CAST(c0 + c1 AS BIGINT) AS carried, round({_x('(n - c0 - c1)')} + {_x('c0')} + {_x('c1')}, 6) AS entropy FROM (SELECT sum(n_sym) AS n, coalesce(sum({_cc.format(0)}) FILTER (coalesce(home, 99) > {i}), 0) AS c0, coalesce(sum({_cc.format(1)}) FILTER (coalesce(home, 99) > {i}), 0) AS c1 FROM home)" for i in range(3)),
    "rate_curve": sql._with(sql._sym("li_zero_tax")) + f"SELECT d AS inverse_eps, b0, round(h, 6) AS entropy, round(k0 / b0, 6) AS flat, round(k0 / b0 + lv, 6) AS ladder, round(h + (2 + log2(3)) / d, 6) AS bound, k0 / b0 + lv < 1 AS below_raw FROM (SELECT CAST(d AS BIGINT) AS d, CAST(b0 AS BIGINT) AS b0, h, ceil((h + 1.0 / CAST(d AS DOUBLE)) * b0) AS k0, (16 * d + 8 * b0 * 2) / CAST(16 * d * b0 AS DOUBLE) AS lv FROM (SELECT {_h} AS h FROM law, nn), (VALUES {', '.join(f'({d}, {b})' for d, b in RATES)}) v(d, b0))",
    "entropy_gap_check": sql._with(sql._sym("li_flag"), sql._blk(32), sql._set(1, 2)) + f"SELECT blocks, round(gap, 6) AS gap, round((2 + w) * 0.5, 6) AS bound, gap <= (2 + w) * 0.5 AS holds FROM (SELECT count(*) AS blocks, max(abs({' + '.join(f'CASE WHEN {_cc.format(i)} > 0 THEN -{_cc.format(i)} / CAST(length(body) AS DOUBLE) * log2({_cc.format(i)} / CAST(length(body) AS DOUBLE)) ELSE 0 END' for i in range(3))} - (SELECT {_h} FROM law, nn))) AS gap FROM st WHERE settled), (SELECT max(log2(CAST(n AS DOUBLE) / c)) AS w FROM law, nn)",
    "flat_error_bound": f"SELECT (SELECT count(*) FROM ({sql._demo()} SELECT * FROM st WHERE NOT settled)) AS failed, round(1 - m, 6) AS open_probability, round(least(1.0, nn / 128.0 * (1 - m)), 6) AS error_bound FROM (SELECT exact_m AS m, nn FROM ({sql.ORACLES['settled_mass_vs_exact'].replace('round(sum(m), 6) AS exact', 'sum(m) AS exact_m, (SELECT n FROM nn) AS nn')}))",
}
