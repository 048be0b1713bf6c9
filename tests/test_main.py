"""Methods against exact answers, golden trajectories and invariants."""

from pathlib import Path

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from turnstile_cover import queries as Q
from turnstile_cover.functions.hashing import PRIME, Seed, poly4
from turnstile_cover.operators import baselines, cells, checkpoints, countsketch, coverage, fingerprint, generalsketch, greedy, l0, l0sampler, measures, moments, neighbours, rowsample, targeted
from turnstile_cover.plans import workloads
from turnstile_cover.plans.params import Params, moment_samples
from turnstile_cover.sources import features
from turnstile_cover.sources.matrix import WORKLOADS, change_to_updates, encode_column, net

GOLDEN = {"c1": (98, 26, 16, 42, 39), "c1t": (42, 98, 37, 16, 26), "c4t": (23, 10, 18, 76, 7), "c6": (150, 329, 75, 78, 59)}
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_hash_matches_its_python_form(spark):
    seed = Seed.of(3)
    got = [r[0] for r in spark.range(50).select(poly4("id", seed)).collect()]
    assert got == [seed.value(x) for x in range(50)] and max(got) < PRIME


@pytest.mark.parametrize("name", GOLDEN)
def test_golden_covers(spark, sf, name):
    got = [r["col"] for r in greedy.cover_df(net(WORKLOADS[name][0](spark, sf)), 5).collect()]
    assert tuple(got) == GOLDEN[name]


def test_worked_vector(spark):
    x = spark.createDataFrame([(v,) for v in (1, 5, 5, 3, -2, 3, 3, 3)], "x long")
    assert [int(moments.fp(x, p).first()[0]) for p in (0, 1, 2, 3)] == [4, 8, 22, 74]
    assert [int(moments.complement_exact(x, p).first()[0]) for p in (2, 3)] == [42, 438]


def test_states_add_subtract_and_forget(spark):
    u = spark.createDataFrame([(i, i % 3, 1 + i % 2) for i in range(300)], "i long, j long, c long")
    a, b = u.where("i % 2 = 0"), u.where("i % 2 = 1")
    whole = l0.build(u, ["j"], slots=64, levels=10)
    parts = cells.merge(l0.build(a, ["j"], slots=64, levels=10), l0.build(b, ["j"], slots=64, levels=10))
    assert rows(whole) == rows(parts)
    assert cells.subtract(whole, parts).count() == 0
    gone = u.unionByName(u.withColumn("c", -F.col("c")))
    assert l0.build(gone, ["j"]).count() == 0 and l0sampler.build(gone, ["j"]).count() == 0


def test_shift_is_the_state_of_the_shifted_vector(spark):
    u = spark.range(200).select(F.lit(0).alias("g"), F.col("id").alias("i"), (F.col("id") % 5).alias("c"))
    ones = u.withColumn("c", F.lit(1).cast("long"))
    moved = u.withColumn("c", F.col("c") - 3)
    assert rows(cells.shift(l0.build(u, ["g"]), l0.build(ones, ["g"]), 3)) == rows(l0.build(moved, ["g"]))


def test_l0_and_sampler(spark):
    u = spark.range(5000).select(F.lit(0).alias("g"), F.col("id").alias("i"), (F.col("id") % 7 - 3).alias("c"))
    true = 5000 - len([x for x in range(5000) if x % 7 == 3])
    est = l0.estimate(l0.build(u, ["g"]), ["g"]).first()["l0"]
    assert abs(est - true) / true < 0.1
    got = l0sampler.draw_batch(l0sampler.build(u, ["g"], size=128), ["g"], 128).collect()
    assert got and all(r["v"] == r["i"] % 7 - 3 != 0 and r["status"] == "OK" for r in got)


def test_overfull_table_says_fail():
    s = tuple(Seed.of(1, n) for n in (11, 12, 13))
    mark, size, table = Seed.of(1, 10), 4, {}
    for x in range(40):
        for p, seed in enumerate(s):
            c = table.setdefault(p * size + seed.value(x) % size, [0, 0, 0])
            c[0], c[1], c[2] = c[0] + 1, c[1] + x, c[2] + mark.value(x)
    _, complete = cells.peel(np.array(list(table)), *(np.array([v[n] for v in table.values()]) for n in range(3)), size, mark, s)
    assert not complete


def test_countsketch_is_exact_for_few_keys(spark):
    u = spark.range(400).select((F.col("id") % 20).alias("i"), F.lit(1).cast("long").alias("c"))
    got = countsketch.estimate(countsketch.build(u, "i"), u.select("i").distinct(), "i").collect()
    assert {r["estimate"] for r in got} == {20.0}


def test_sample_keeps_cap_and_budget(spark, sf):
    a, p = net(WORKLOADS["c1"][0](spark, sf)), Params.explicit(2000, 100, 5, 10, 2000)
    s = rowsample.capped_sample(a, p)
    most = s.groupBy("i").count().agg(F.max("count")).first()[0]
    assert most <= 10 and 2000 <= s.count() < 2010


def test_sketch_answer_is_close_to_greedy(spark, sf):
    u, p = WORKLOADS["c4t"][0](spark, sf), Params.practical(200, 100, 3, 0.3)
    cols = coverage.max_coverage_batch(u, p).first()["cols"]
    full = [r["col"] for r in greedy.cover_df(net(u), 3).collect()]
    assert len(cols) == 3 and measures.ratio(net(u), list(cols), full).first()["ratio"] > 0.85
    found = coverage.recover(coverage.build_sketch(u, p)[0], p)
    assert found.select("i", "j").join(net(u), ["i", "j"], "left_anti").count() == 0


def test_keys_past_the_fixed_sizes(spark):
    u = spark.createDataFrame([(3, 1500, 1), (4, 476, 1)], "i long, j long, c long")
    p = Q.sized(u)
    assert {tuple(r)[1:] for r in coverage.recover(coverage.build_sketch(u, p)[0], p).collect()} == {(3, 1500), (4, 476)}
    assert Q.sized(u.where("j = 476")) == Q.P1
    with pytest.raises(Exception, match="does not fit the width"):
        coverage.build_sketch(u, Q.P1)[0].count()


def test_local_greedy_equals_rounds(spark, sf):
    a = net(WORKLOADS["c4"][0](spark, sf))
    pdf = a.toPandas()
    want = [tuple(r) for r in greedy.cover_df(a, 5).collect()]
    assert greedy.cover_local(pdf, 5) == want == greedy.cover_local(pdf, 5, lazy=False)
    best = baselines.optimum(a, 2).first()["total"]
    assert want[1][3] >= (1 - 1 / np.e) * best


def test_general_golden(spark, sf):
    w = features.people(spark, sf)
    assert [(r["col"], r["total"]) for r in fingerprint.greedy_raw(w, 3).collect()] == [("nation", 107_888_440), ("month", 112_107_515), ("pricebin", 112_453_836)]
    assert [r["total"] for r in fingerprint.greedy_onehot(w, 2).collect()] == [50_432_256, 74_993_663]
    est = fingerprint.estimated_pairs(w.coded(), ["nation", "month"], 15_000).first()["separated"]
    assert abs(est - 112_107_515) / 112_107_515 < 0.02


def test_all_users_are_targets(spark):
    d = "/root/testdata/sf0.001"
    w = features.people(spark, d)
    own = {}
    for uid, f in w.long().collect():
        own.setdefault(uid, set()).add(f)
    sample = {r["uid"] for r in targeted.sampled_rows(w.df, 0.1).select("uid").collect()}
    has = {f: {u for u in sample if f in own[u]} for f in sorted(set().union(*own.values()))}
    want = set()
    for uid, mine in own.items():
        open_, cols, total = set(sample), [], 0
        for _ in range(7):
            gain = {f: len(open_ - h) if f in mine else len(open_ & h) for f, h in has.items() if f not in cols}
            best = max(gain, key=gain.get)  # the first of a tie
            cols.append(best)
            total += gain[best]
            open_ = open_ & has[best] if best in mine else open_ - has[best]
        want.add((uid, ",".join(cols), total))
    assert {tuple(r) for r in Q.QUERIES["targeted_all_users"](spark, d).collect()} == want


def test_targets_with_shared_rows_equal_bitmaps(monkeypatch):
    """Weighted rows for all targets at once, with ties, against one bitmap greedy a target."""
    rng = np.random.default_rng(0)
    for few in (0, targeted.FEW):
        monkeypatch.setattr(targeted, "FEW", few)
        for _ in range(30):
            sizes = rng.integers(1, 5, rng.integers(1, 5))
            attribute = np.repeat(np.arange(len(sizes)), sizes)
            first = np.concatenate(([0], np.cumsum(sizes)[:-1]))
            codes = np.unique(np.stack([f + rng.integers(0, n, 20) for f, n in zip(first, sizes)], 1), axis=0).astype(np.int16)
            w = rng.integers(0, 4, len(codes)).astype(np.int32)
            w[0] = 1
            every, k = w + rng.integers(0, 3, len(codes)).astype(np.int32), int(rng.integers(1, 8))
            has = np.array([(codes == f).any(1) for f in range(len(attribute))])
            bits, all_ = targeted.bitmaps(np.repeat(has, w, 1)), targeted.bitmaps(np.ones((1, w.sum()), bool))[0]
            picks, won, left = targeted.shared_greedy(codes, w, every, codes, k, attribute)
            assert (targeted.shared_greedy(codes, w, every, codes, k, attribute, False)[2] == left).all()
            for t, row in enumerate(codes):
                want = targeted.greedy_bits(targeted.difference(bits, [int(x) for x in row], all_), all_, k)
                assert (list(picks[t]), list(won[t])) == want
                same = np.ones(len(codes), bool)
                for r, f in enumerate(want[0]):
                    same &= has[f] == (f in row)
                    assert left[t, r] == every[same].sum()


def test_rounds_by_groups_equal_shared_rows(monkeypatch):
    """All groups of a round at a time, whole and in many pieces, with ties, against the rounds of one group at a time."""
    rng = np.random.default_rng(3)
    for trial in range(60):
        monkeypatch.setattr(targeted, "CELLS", (1 << 17, 40)[trial % 2])
        spans = [int(x) for x in rng.integers(1, 6, rng.integers(1, 6))]
        raw = np.stack([rng.integers(0, n, 40) for n in spans], 1)
        first, number = targeted.same_rows(raw, spans)
        codes, every = raw[first], np.bincount(number)
        assert (codes[number] == raw).all() and len(np.unique(raw, axis=0)) == len(codes)
        w, k = rng.binomial(every, 0.6), int(min(rng.integers(1, 8), sum(spans)))
        places = (codes + np.cumsum([0, *spans[:-1]])).astype(np.int32)
        want = targeted.shared_greedy(places, w, every, places, k, np.repeat(np.arange(len(spans)), spans), False)[2]
        got = np.full((len(codes), k), -1)
        for r, who, left in targeted.left_by_round(codes, w.astype(float), every, np.arange(len(codes)), [], k, spans):
            got[who, -r - 1 if r < 0 else r - 1 : None if r < 0 else r] = left[:, None]
        assert (got == want).all()
    assert len(targeted.same_rows(rng.integers(0, 9, (500, 30)), [1 << 20] * 30)[0]) == 500  # rows past 62 bits


def test_totals_send_no_rows_whole(spark, monkeypatch):
    """The totals of a sweep equal every target's own, without the table of different rows that went to the driver before."""
    w = features.people(spark, "/root/testdata/sf0.001")
    c = w.codes()
    alone = targeted.sweep(w, c.df.select("uid"), 4, [0.1, 0.5], 2, codes=c).groupBy("rate", "seed", "k").agg(F.avg("separated").alias("separated"), F.min("separated").alias("least"), F.count("*").alias("users"))
    want = rows(alone.select("rate", "seed", "k", F.round("separated", 6), "least", "users"))

    def whole(*_):
        raise AssertionError("rows sent whole")

    monkeypatch.setattr(targeted, "different_rows", whole)
    got = targeted.sweep_totals(c, 4, [0.1, 0.5], 2)
    assert rows(got.select("rate", "seed", "k", F.round("separated", 6), "least", "users")) == want and len(want) == 16


def test_sweep_of_repeated_users(spark, tmp_path):
    """Sixty times the users with shifted keys, 936 million cells: an error before."""
    d, n = "/root/testdata/sf0.01", 60
    w = features.people(spark, d)
    more = w.over(w.df.withColumn("uid", F.explode(F.sequence(F.col("uid"), F.col("uid") + (n - 1) * 1_000_000, F.lit(1_000_000)))))
    c = more.codes()
    got = targeted.sweep_totals(c, 2, [0.6, 0.4, 0.2], 10)
    assert {(r["users"], r["k"]) for r in got.collect()} == {(15_000 * n, 1), (15_000 * n, 2)}


def test_sweeps_equal_plain_counts(spark):
    d = "/root/testdata/sf0.001"
    w = features.people(spark, d)
    c = w.codes()
    n = c.df.count()
    swept = targeted.sweep(w, c.df.where("uid < 40").select("uid"), 4, [0.3], 2, codes=c).where("seed = 2")
    got = {(r["uid"], r["k"]): r["separated"] for r in swept.collect()}
    own = {}
    for uid, f in w.long().collect():
        own.setdefault(uid, set()).add(f)
    picks = targeted.fingerprint_all(w, c.df.where("uid < 40").select("uid"), 4, 0.3, 2, codes=c).collect()
    for r in picks:
        for k in range(1, 5):
            cols = r["cols"][:k]
            same = sum({f for f in cols if f in own[u]} == {f for f in cols if f in own[r["uid"]]} for u in own)
            assert got[r["uid"], k] == n - same
    runs = [(0, [(3, 5), (5, 2), (0, 1)]), (1, [(4, 1995)])]
    pairs = {(r["run"], r["k"]): r["separated"] for r in fingerprint.prefix_pairs(c, runs).collect()}
    for run, chosen in runs:
        for k in range(1, len(chosen) + 1):
            names = [c.name(w.attributes[a], v) for a, v in chosen[:k]]
            assert pairs[run, k] == fingerprint.onehot_pairs(w, names).first()[0]
    swept = {(r["sample_rows"], r["seed"]): [c.name(w.attributes[p["a"]], p["v"]) for p in r["picks"]] for r in fingerprint.sweep_rowhash(c, 5, [100, 300], 2, n).collect()}
    for (size, seed), names in swept.items():
        alone = fingerprint.select_rowhash(w, 5, size, seed, n).orderBy("round").collect()
        assert [r["col"] for r in alone] == names
    table = workloads.general_sweep(spark, d, "F1", rows=[300], k=6, seeds=2).collect()
    assert len(table) == 6 and all(0.8 < r["least"] <= r["ratio"] <= 1.001 for r in table)
    assert {r["targets"] for r in workloads.targeted_sweep(spark, d, "F3", [0.6], k=2, seeds=2).collect()} == {spark.read.parquet(f"{d}/events.parquet").select("user_id").distinct().count()}


def test_general_sketch_is_linear_and_selects(spark):
    d = "/root/testdata/sf0.001"
    w = features.people(spark, d)
    u, users = Q.five_columns(w), w.df.select(F.col("uid").alias("i"))
    n = users.count()
    rng = u.withColumn("wrong", F.col("c") + 3)
    there_and_back = u.unionByName(rng.select("i", "j", F.col("wrong").alias("c"))).unionByName(rng.select("i", "j", (-F.col("wrong")).alias("c"))).repartition(7)
    for sampler in ("l0", "rowhash"):
        sizes = generalsketch.GeneralSizes(n, sampler, size=256, rows=600, slots=256, levels=12)
        whole, again = (generalsketch.build(x, users, sizes) for x in (u, there_and_back))
        parts = generalsketch.merged(*(generalsketch.build(u.where(f"i % 2 = {x}"), users, sizes) for x in (0, 1)))
        for a, b, c in zip(whole.tables(), again.tables(), parts.tables(), strict=True):
            assert rows(a) == rows(b) == rows(c)
        picked = [r["col"] for r in generalsketch.select(there_and_back, users, 2, sizes).orderBy("round").collect()]
        best = [r["total"] for r in fingerprint.greedy_raw(w, 2).collect()]
        assert fingerprint.separated_pairs(w.df, [Q.FIVE[x] for x in picked]).first()[0] >= 0.8 * best[1]
    with pytest.raises(ValueError):
        generalsketch.select(u, users, 3, sizes, copies=2)


def test_wide_ids_and_upper_row_levels(spark):
    base = 1 << 39
    u = spark.range(3000).select((F.lit(base) + F.col("id") * 977).alias("i"), (F.col("id") % 50 * 19_999).alias("j"), F.lit(1).cast("long").alias("c"))
    u = u.unionByName(u.where("i % 10 = 0").withColumn("c", -F.col("c")))
    p = Params.explicit(1 << 40, 10**6, 5, 10, 2000, buckets=32, slots=96, levels=8)
    assert p.wide and not Q.P1.wide
    found = coverage.recover(coverage.build_sketch(u, p)[0], p)
    a = net(u)
    assert found.select("i", "j").join(a, ["i", "j"], "left_anti").count() == 0 and found.where("m = 0").count() > 0.8 * a.count()
    cols = coverage.max_coverage_batch(u, p).first()["cols"]
    full = [r["col"] for r in greedy.cover_df(a, 5).collect()]
    assert measures.ratio(a, list(cols), full).first()["ratio"] > 0.9
    with pytest.raises(ValueError):
        Params.practical(1 << 50, 1 << 20, 3)
    # dense rows overfill the one table of row level 0, whose few entries say less than whole rows of an upper level
    pairs = spark.range(600).withColumnRenamed("id", "i").crossJoin(spark.range(40).withColumnRenamed("id", "j"))
    dense = pairs.where(F.pmod(F.hash("i", "j"), F.lit(1000)) < 50 + 8 * F.col("j")).withColumn("c", F.lit(1).cast("long"))
    best = [r["col"] for r in greedy.cover_df(dense, 2).collect()]
    got = coverage.max_coverage_batch(dense, Params.explicit(600, 40, 2, 40, 10_000, buckets=1, slots=24, levels=6, reps=1, seed=3)).first()
    assert got["m"] > 0 and measures.ratio(dense, list(got["cols"]), best).first()["ratio"] > 0.85


def test_measures(spark):
    assert measures.speedup(10.0, 2.0, 3.0) == {"speedup": 5.0, "speedup_with_build": 2.0}
    assert measures.timed(lambda: spark.range(10)) > 0 and measures.fanout(Q.P1) == {"recovery": 9, "l0": 3}
    assert measures.exchange_bytes(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count()) > 0
    one = lambda x: spark.createDataFrame([(x,)], "complement double")
    assert measures.rel_err(one(9.0), one(10.0)).first()["rel_err"] == 0.1
    over = measures.over_seeds(lambda s: spark.createDataFrame([(float(s),)], "v double"), "v", range(5)).first()
    assert (over["mean"], over["least"]) == (2.0, 0.0)
    x = spark.createDataFrame([(1, 0, 60.0, 50.0), (2, 0, 1.0, 50.0), (0, 0, 30.0, 50.0)], "x long, b long, f double, f_b double")
    assert [r["x"] for r in moments.keep_large(x, 100, 0.9).collect()] == [1]
    u = spark.createDataFrame([(i, 0, 1) for i in range(30)] + [(i, 1, 1) for i in range(4000)], "i long, j long, c long")
    small = {r["j"]: (r["exact"], r["l0"]) for r in l0.exact_small(l0sampler.build(u, ["j"]), ["j"]).collect()}
    assert small[0] == (True, 30) and small.get(1, (False, None)) == (False, None)
    got = l0sampler.draw(l0sampler.build(u, ["j"]), ["j"]).collect()
    assert len(got) == 2 and all(r["v"] == 1 and r["status"] == "OK" for r in got)


def test_shared_folder_and_release(spark):
    from turnstile_cover.operators import checkpoints

    at = checkpoints.mark()
    a, b = checkpoints.cut(spark.range(5)), checkpoints.cut(spark.range(6))
    assert checkpoints.release(spark, at, keep=(b,)) == 1 and b.count() == 6
    with pytest.raises(Exception, match="(?i)not exist|not found"):
        a.count()

    class Far:
        conf = type("C", (), {"get": staticmethod(lambda *x: None)})
        sparkContext = type("S", (), {"master": "spark://x", "getConf": staticmethod(lambda: type("D", (), {"get": staticmethod(lambda *x: None)}))})

    with pytest.raises(RuntimeError, match="checkpoint"):
        checkpoints.shared_folder(Far())


def test_stream_increments_compact(spark, sf):
    import uuid

    from turnstile_cover.operators.checkpoints import shared_folder
    from turnstile_cover.streaming import streams

    folder = f"{shared_folder(spark)}/compact_{uuid.uuid4().hex}"
    streams.maintain(streams.read_stream(spark, streams.stage_events(spark, sf, f"in_{uuid.uuid4().hex}")), streams.column_cells, folder)
    before = rows(streams.snapshot(spark, folder))
    assert streams.compact(spark, folder) >= 1 and rows(streams.snapshot(spark, folder)) == before


def test_moment_branches(spark):
    got = {r["name"]: r["branch"] for r in Q.QUERIES["complement_branches"](spark, "/root/testdata/sf0.01").collect()}
    assert got["all_distinct"] == "all_small" and got["heavy"] == "dominant" and got["half"] == "middle"
    equal = Q.branch_vectors(spark.range(2000).withColumnRenamed("id", "uid"))["all_equal"]
    assert moments.complement_of_sample(equal, 2000, 2, 500).first()["complement"] == 0.0


def test_insertion_only_sketches_miss_deletions(spark):
    u = spark.createDataFrame([(i, 0, c) for i in range(100) for c in ((1, -1) if i < 60 else (1,))], "i long, j long, c long")
    assert net(u).count() == 40
    assert baselines.hll_union(u, [0]).first()[0] > 90 and baselines.bitmap_union(u, [0]).first()[0] == 100


def test_parameters_and_encoding(spark):
    with pytest.raises(ValueError):
        Params.practical(10, 3, 4)
    assert Params.theory(1000, 50, 5, 0.2).budget <= 50_000 and moment_samples(0.01, 2, 0.1) > 10**6
    df = spark.createDataFrame([(0,), (-4,), (None,)], "x int").select(encode_column(F.col("x"), "int").alias("c"))
    assert [r[0] for r in df.collect()] == [1, -5, -1]
    e = spark.createDataFrame([(1, 1, 5, 0), (1, 1, 3, 1)], "u long, f long, v long, t int")
    assert sorted(r["c"] for r in change_to_updates(e, "u", "f", "v", ["t"]).collect()) == [-2, 5]


FAST = ["op_scan_project", "op_hash_sample", "op_join_asof", "op_agg_cube_pairs", "op_win_range_1h", "op_math_hash", "op_sql_udf_hash", "op_set_except", "op_pivot_features", "op_map_features", "cover_capped_sample_c1", "l0_per_column_c1t", "targeted_exact_f1_u0", "general_rowhash_f1_300", "stream_session_users", "stream_cells_events", "sketch_subtract_window"]


@pytest.mark.parametrize("name", FAST)
def test_query_equals_its_sql(spark, sf, duck, name):
    got = Q.QUERIES[name](spark, sf)
    want = duck.execute(Q.ORACLE[name])
    names = [d[0] for d in want.description]
    assert sorted(got.columns) == sorted(names)
    key = lambda r: tuple(map(str, r))
    assert sorted((tuple(r) for r in got.select(*names).collect()), key=key) == sorted(want.fetchall(), key=key)


def test_moments_past_a_long_stay_whole(spark):
    """Equal values past the cube root of 2^63: the cast to a long was an error."""
    x = spark.range(2_200_000).select((F.col("id") % 2).alias("x"))
    got = moments.as_long(moments.complement_exact(x, 3), "complement", 2_200_000, 3)
    assert int(got.first()[0]) == 2_200_000**3 - 2 * 1_100_000**3
    assert moments.as_long(moments.fp(x, 2), "fp", 2_200_000, 2).schema["fp"].dataType.simpleString() == "bigint"


def test_counts_past_a_table_are_exact(spark):
    u = spark.createDataFrame([(i, 0, 1) for i in range(30)] + [(i, 1, 1) for i in range(4000)] + [(5, 1, -1)], "i long, j long, c long")
    assert rows(l0.exact_all(u, ["j"])) == [(0, 30, True), (1, 3999, True)]


def test_failed_draws_are_drawn_again(spark):
    """Tables so small that some of many groups fail at first."""
    u = spark.range(6000).select((F.col("id") % 600).alias("j"), F.col("id").alias("i"), F.lit(1).cast("long").alias("c"))
    once = l0sampler.draw_batch(l0sampler.build(u, ["j"], size=8), ["j"], 8)
    assert measures.failure_rate(once, ["j"]).first()["failures"] > 0
    got = l0sampler.draw_again(u, ["j"], size=8, copies=8)
    assert tuple(measures.failure_rate(got, ["j"]).first()) == (600, 0, 0.0)
    assert got.groupBy("j").agg(F.countDistinct("lvl").alias("n")).where("n > 1").isEmpty()


def test_seeds_share_one_shuffle(spark):
    u = spark.range(3000).select((F.col("id") % 20).alias("j"), (F.col("id") * 7).alias("i"), F.lit(1).cast("long").alias("c"))
    u = u.unionByName(u.where("i % 5 = 0").withColumn("c", -F.col("c")))
    want = measures.over_seeds(lambda x: measures.l0_error(u, "j", seed=x).agg(F.max("rel_err").alias("worst")), "worst")
    got = measures.l0_over_seeds(u, "j")
    assert got.first() == want.first() and measures.exchange_bytes(got) < measures.exchange_bytes(want) / 4


def test_sign_sketch_hashes_equal_values_once(spark):
    x = spark.range(40_000).select((F.col("id") % 9).alias("x"))
    plan = moments.f2_sign_sketch(x)._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" in plan and plan.index("Generate") < plan.rindex("Aggregate")


@pytest.mark.parametrize("name", ["complement_branches", "op_recursive_levels", "update_fanout"])
def test_query_reads_a_table(spark, sf, duck, name):
    got = Q.QUERIES[name](spark, sf)
    want = duck.execute(Q.ORACLE[name])
    names = [c[0] for c in want.description]
    assert sorted(map(tuple, got.select(*names).collect())) == sorted(want.fetchall())
    assert got.inputFiles()


@pytest.mark.parametrize("name", ["cover_sketch_cells_c1t", "sketch_size_c1t", "cover_sketch_recovered_c1t", "cover_answer_c1t"])
def test_cells_past_the_fixed_sizes_equal_sql(spark, tmp_path, name):
    """Suppliers past the width of the SQL's codes and parts past its rows."""
    import duckdb

    con = duckdb.connect()
    con.execute(f"COPY (SELECT * REPLACE (l_suppkey + 1500 * (l_orderkey % 3) AS l_suppkey, l_partkey + 30000 * (l_orderkey % 3) AS l_partkey) FROM '/root/testdata/sf0.001/lineitem.parquet') TO '{tmp_path}/lineitem.parquet' (FORMAT parquet)")
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet'")
    want = con.execute(Q.ORACLE[name])
    names = [c[0] for c in want.description]
    assert sorted(map(tuple, Q.QUERIES[name](spark, str(tmp_path)).select(*names).collect())) == sorted(want.fetchall())


@pytest.mark.parametrize("name", ["cover_sketch_recovered_c1t", "cover_answer_c1t"])
def test_entries_with_equal_codes_in_a_bucket_equal_sql(spark, tmp_path, name):
    """Rows i and i + 1 in one bucket, with columns on both sides of the width: their codes are equal, so no table told them apart."""
    bucket = lambda i: Seed.of(Q.P1.seed, 30).value(i) % Q.P1.buckets
    pair = next(i for i in range(1, 20_000) if bucket(i) == bucket(i + 1))
    con = duckdb.connect()
    con.execute(f"COPY (SELECT {pair} + r AS l_partkey, j AS l_suppkey, CASE WHEN j % 5 = 0 THEN 'R' ELSE 'N' END AS l_returnflag FROM range(2) a(r), range(6000) b(j)) TO '{tmp_path}/lineitem.parquet' (FORMAT parquet)")
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet'")
    want = con.execute(Q.ORACLE[name])
    names = [c[0] for c in want.description]
    assert sorted(map(tuple, Q.QUERIES[name](spark, str(tmp_path)).select(*names).collect())) == sorted(want.fetchall())


def test_held_entries_equal_sql_where_tables_share_slots(spark):
    """Few slots and many levels, so that a table is half empty levels below the one that its entries' number gives."""
    p = Params.explicit(500, 60, 3, 60, 10_000, slots=8, buckets=3, levels=9)
    a = spark.range(0, 9000).selectExpr("(id * 7919 + 13) % 500 AS i", "(id * id + id * 31) % 60 AS j").distinct()
    entries = a.toPandas()  # noqa: F841
    want = sorted(duckdb.sql(coverage.recovered_sql("SELECT i, j, 1 AS v FROM entries", p)).fetchall())
    assert rows(coverage.held(a, p).select("m", "i", "j")) == want and want


def test_vectors_are_covered_in_blocks(spark, tmp_path):
    """Nulls, no dimension, other lengths, zeros, copies, an id with two vectors, and pairs at the limit itself."""
    r = np.random.default_rng(3)
    data = [(i, [float(np.float32(x)) for x in r.normal(size=5)]) for i in range(300)]
    data += [(300 + i, [1.0, 0.0, 0.0, 0.0, 0.0] if i % 2 else [1.0, 2.0, 2.0, 4.0, 0.0]) for i in range(40)]  # cosine 0.2 exactly
    data += [(400, None), (401, [1.0, None, 0.0, 0.0, 0.0]), (402, [0.0] * 5), (403, []), (404, [1.0, 1.0]), (405, [1.0, 0.9]), (7, [9.0, 0.0, 0.0, 0.0, 0.0])]
    spark.createDataFrame(data, "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    want = greedy.cover_df(net(WORKLOADS["c6"][0](spark, str(tmp_path))), 9)
    v = spark.read.parquet(f"{tmp_path}/embeddings.parquet").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))
    assert neighbours.cover(v, 9, rows=32).collect() == want.collect()
    few = v.where("id = 3 OR id = 402")
    assert [tuple(x) for x in neighbours.cover(few, 5).collect()] == [(1, 3, 2, 2), (2, 402, 0, 2)]


def test_pairs_of_vectors_are_not_written(spark, tmp_path, monkeypatch):
    """A twentieth of all pairs are entries; they were written as rows in every round."""
    written = []
    monkeypatch.setattr(checkpoints, "noted", lambda path: written.append(path) or path)
    r = np.random.default_rng(4)
    spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(r.normal(size=(3000, 64)))], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    Q.QUERIES["cover_greedy_c6"](spark, str(tmp_path)).collect()
    size = lambda path: sum(f.stat().st_size for f in Path(path).rglob("*.parquet"))
    assert sum(map(size, written)) < 2 * size(f"{tmp_path}/embeddings.parquet")


def test_lazy_rounds_and_packed_samples(spark):
    """Bounds, few features kept, codes that pass one long, missing values and repeated users; samples wrote all columns for every seed."""
    r = np.random.default_rng(5)
    data = [(i, int(r.integers(3)), int(r.integers(-2, 40)), int(r.integers(1 << 40)) << 20 if i % 5 else -7, int(r.integers(1 << 40)) << 20 if i % 3 else 8, None if i % 11 == 0 else int(r.integers(4))) for i in range(2000)]
    df = spark.createDataFrame(data, "uid long, a long, b long, c long, d long, e long")
    w = features.Wide(df, ("a", "b", "c", "d", "e"), frozenset(), "")
    c = w.codes()
    assert len(fingerprint.packing(c)) > 1
    want = fingerprint.greedy_onehot(w, 9, 2000, c).collect()
    for more in ({"batch": 2}, {"most": 3, "batch": 2}, {"most": 1}):
        assert fingerprint.greedy_onehot(w, 9, 2000, c, lazy_from=0, **more).collect() == want
    swept = {(x["sample_rows"], x["seed"]): [(p["a"], p["v"]) for p in x["picks"]] for x in fingerprint.sweep_rowhash(c, 6, [50, 700, 5000], 2, 2000).collect()}
    assert len(swept) == 6
    for (size, seed), picks in swept.items():
        part = fingerprint.row_sample(c.df, size, 2000, seed).toPandas()
        found = [(i, int(v)) for i, a in enumerate(c.attributes) for v in sorted(part[a].dropna().unique())]
        codes = np.stack([(part[c.attributes[i]] == v).to_numpy() for i, v in found], axis=1).astype(np.int8)
        assert [found[x[1]] for x in fingerprint.local_onehot(codes, list(range(len(found))), 6)] == picks
    written = fingerprint.sweep_rowhash(features.people(spark, "/root/testdata/sf0.01").codes(), 2, [600], 10, 15_000)
    assert measures.exchange_bytes(written) < 10 * 600 * 40


def test_coverage_table_writes_its_entries_once(spark):
    """Every method computed the entries anew, and all tables of all rounds stayed."""
    since = checkpoints.mark()
    table = workloads.coverage_table(spark, "/root/testdata/sf0.001").collect()
    assert [r["method"] for r in table] == ["sketch", "capped_sample", "bucketed_sample"] and all(0 < r["ratio"] <= 1.2 for r in table)
    assert checkpoints.mark() == since + 1
    checkpoints.release(spark, since)
