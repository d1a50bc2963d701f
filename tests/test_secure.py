import numpy as np
import pytest
from pyspark.sql import functions as F

from veilmatch.functions.text import MAP
from veilmatch.operators import bloom, cost, match, mpc, score, secure, shares
from veilmatch.operators.registry import Registry

U = np.uint64
KEY = "test"
EMPTY = "rec_id long, owner string, first_name string, last_name string, birth_name string, city string, postcode int, birth_year int, birth_month int, birth_day int"


@pytest.fixture(scope="module")
def sides(spark, sf):
    r = Registry.of(spark, sf)
    return score.encode(r.left).where("rec_id < 10000040").persist(), score.encode(r.right).where("rec_id < 20000040").persist()


def rows(df):
    return {tuple(r[c] for c in ("x_id", "y_id", "num", "den")) for r in df.collect()}


def clear(x, y, tau):
    return rows(match.link_all(x, y, tau))


@pytest.mark.parametrize("order,block", [("tree", 13), ("scan", 256)])
def test_private_run_equals_the_clear_run(sides, order, block):
    x, y = sides
    assert rows(secure.link_all(x, y, 7000, key=KEY, order=order, block=block)) == clear(x, y, 7000)


def test_no_threshold_and_fresh_keys(sides):
    x, y = sides
    assert rows(secure.link_all(x, y, None)) == clear(x, y, None)


def test_one_record_and_empty_sides(sides):
    x, y = sides
    one = x.agg(F.min("rec_id")).first()[0]
    assert rows(secure.link_one(x, one, y, 7000, key=KEY)) == {r for r in clear(x, y, 7000) if r[0] == one}
    assert secure.link_all(x.where("false"), y, 7000, key=KEY).count() == 0
    assert secure.link_all(x, y.where("false"), 7000, key=KEY).count() == 0


def test_missing_records_have_no_partner(spark):
    people = spark.createDataFrame([(1, "l", None, None, None, None, None, None, None, None), (2, "l", "anna", "meier", None, "bonn", 1, 1980, 1, 2)], EMPTY)
    others = spark.createDataFrame([(7, "r", None, None, None, None, None, None, None, None), (8, "r", "anna", "meier", None, "bonn", 1, 1980, 1, 2), (9, "r", "anna", "meier", None, "bonn", 1, 1980, 1, 2)], EMPTY)
    got = {r.x_id: r.y_id for r in secure.link_all(score.encode(people), score.encode(others), 7000, key=KEY, block=2).collect()}
    assert got == {1: None, 2: 8}


def test_scores_dice_and_counts_are_the_clear_ones(sides):
    x, y = sides
    assert rows(secure.opened_scores(x, y, KEY, block=40)) == rows(match.scored(match.pairs(x, y)))
    want = {(a.rec_id, b.rec_id): len(set(a.name_pos or ()) & set(b.name_pos or ())) for a in x.select("rec_id", "name_pos").collect() for b in y.select("rec_id", "name_pos").limit(20).collect()}
    got = {(r.x_id, r.y_id): (r.name_num, r.name_den) for r in secure.opened_dice(x, y, KEY, block=64).collect()}
    assert all(got[k][0] == 2 * n for k, n in want.items()) and len(got) == x.count() * y.count()
    pairs = x.alias("a").crossJoin(y.limit(3).alias("b")).select((F.col("a.rec_id") * 10**9 + F.col("b.rec_id")).alias("id"), F.col("a.name_pos").alias("a"), F.col("b.name_pos").alias("b")).persist()
    plain = {r.id: len(set(r.a or ()) & set(r.b or ())) for r in pairs.collect()}
    for mode in ("arith", "bits"):
        assert {r.id: r["shared"] for r in secure.and_counts(pairs, mode, KEY).collect()} == plain


def test_fixed_operand_opens_once():
    rng = np.random.default_rng(3)
    x, y = rng.integers(0, 2, MAP).astype(U), rng.integers(0, 2, (9, MAP)).astype(U)
    s = mpc.Session(KEY)
    assert (mpc.reveal(s.multiply_fixed(s.split(x), s.split(y))) == x * y).all()
    assert s.bytes_["input", 0, 1, "online"] == 8 * 10 * MAP


@pytest.mark.parametrize("m", [1, 25])
def test_ledger_equals_the_closed_form(spark, sides, m):
    x, y = sides
    y = y.orderBy("rec_id").limit(m).persist()
    one = x.orderBy("rec_id").limit(1)
    counted = secure.traffic(one, y, 7000, key=KEY, block=128).collect()
    got = {(r.step, r.src, r.dst): r.n_bytes for r in counted}
    assert got == {(r.step, r.src, r.dst): r.n_bytes for r in cost.traffic(spark, (m,)).collect()}
    by_step = {r.step: r.n_rounds for r in counted}
    fixed = max(by_step[k] for k in ("dice", "completeness", "equality")) + sum(by_step[k] for k in ("score", "guard", "gate"))
    assert fixed + by_step.get("tournament", 0) == cost.rounds(spark, (m,)).first().n_rounds


def test_maps_are_opened_once_whatever_the_blocks(sides):
    x, y = sides
    n = x.count() + y.count()
    for block in (30,):
        got = {(r.step, r.src): r.n_bytes for r in secure.traffic(x, y, 7000, key=KEY, block=block).collect()}
        assert got["dice", 0] == 8 * 2 * MAP * n


def test_offline_phase_of_the_rival(spark, sides):
    x, y = (bloom.encode(v) for v in sides)
    got = rows(secure.link_all(x, y, 7000, key=KEY, places=bloom.BITS, weights=bloom.WEIGHTS, offline=True))
    assert {r[:2] for r in got} == {r[:2] for r in rows(match.accept(bloom.best_partners(*sides), 7000))}
    for offline in (False, True):
        share = {r.phase: r.share for r in cost.offline_share(secure.traffic(x, y, 7000, key=KEY, places=bloom.BITS, offline=offline)).collect()}
        assert (share.get("offline", 0) > 0) == offline


def test_modelled_time_moves_with_size_and_network(spark):
    got = {(r.profile, r["size"]): r.seconds for r in cost.modelled(spark).collect()}
    assert all(got[p, a] <= got[p, b] for p in "ABC" for a, b in zip(cost.SIZES, cost.SIZES[1:]))
    assert all(got["C", n] < got["A", n] <= got["B", n] for n in cost.SIZES)


def test_shares_of_owners(spark, sides):
    x, _ = sides
    columns = ["postcode", "birth_year", "name_card"]
    p0, p1 = shares.both(x, columns, KEY)
    want = {r[0]: tuple(v or 0 for v in r[1:]) for r in x.select("rec_id", *columns).collect()}
    assert {r[0]: tuple(r)[1:] for r in shares.opened(p0, p1, columns).collect()} == want
    packed = x.select("rec_id", F.array(*[f"n{i}" for i in range(15)]).alias("bits"))
    b0, b1 = shares.both(packed, ["bits"], KEY, bits=True)
    assert {r.rec_id: r.bits for r in shares.opened(b0, b1, ["bits"], bits=True).collect()} == {r.rec_id: r.bits for r in packed.collect()}
    assert shares.shape_only(p0).first() == (0, x.count(), 3)
    some = sorted(want)[:5]
    grants = spark.createDataFrame([(i, "a") for i in some] + [(some[0], "b")], "rec_id long, receiver string")
    assert {r.rec_id for r in shares.revealed(p0, p1, columns, grants, "a").collect()} == set(some)
    assert {r.rec_id for r in shares.revealed(p0, p1, columns, grants, "b").collect()} == {some[0]}
    assert shares.split(x.where("false"), columns, KEY, 1).count() == 0


def test_shares_wrap_and_show_nothing(spark, tmp_path):
    edges = [0, 1, -1, 2**31, 2**62, 2**63 - 1, -(2**63)]
    df = spark.createDataFrame([(i, v) for i, v in enumerate(edges)], "rec_id long, v long")
    p0, p1 = shares.both(df, ["v"], KEY)
    assert [r.v for r in shares.opened(p0, p1, ["v"]).orderBy("rec_id").collect()] == edges
    total = sum(edges) % 2**64
    assert df.agg(shares.ring_sum(F.col("v"))).first()[0] % 2**64 == total
    many = spark.range(20_000).select(F.col("id").alias("rec_id"), F.lit(7).cast("long").alias("v"))
    for party in (0, 1):
        seen = shares.view_uniform(shares.split(many, ["v"], KEY, party), "v").first()
        assert seen.cells == 256 and seen.chi_square < 400
    shares.write(*shares.both(df, ["v"], KEY), f"{tmp_path}/s")
    back = spark.read.parquet(f"{tmp_path}/s")
    assert [r.v for r in shares.opened(back.where("party = 0"), back.where("party = 1"), ["v"]).orderBy("rec_id").collect()] == edges


def test_messages_are_uniform():
    """What the proxies open and what reaches the dealer does not move with the input."""
    seen = []

    class Watched(mpc.Session):
        def _masked(self, u):
            t, rho = super()._masked(u)
            seen.append(t)
            return t, rho

    s = Watched(KEY)
    s.greater(s.split(np.full(50_000, 5, U)), s.split(np.full(50_000, 9, U)))
    counts = np.bincount(seen[0].view(np.uint8), minlength=256)
    assert ((counts - counts.mean()) ** 2 / counts.mean()).sum() < 400
