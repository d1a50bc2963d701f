"""Registered queries of the private method, its rival and its cost, of more workloads, and of relational operators.

All run over whole tables. The private queries have the clear run as their SQL.
"""

from __future__ import annotations

import math
import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from veilmatch.functions import fields, text
from veilmatch.operators import baselines, blocks, bloom, cost, covers, match, quality, score, secure, shares
from veilmatch.operators.registry import Registry
from veilmatch.plans import catalog as C
from veilmatch.plans import oracle as O
from veilmatch.sources.tables import table
from veilmatch.streaming import arrivals

add, ex, ey, bp, truth, kept, TAU = C.add, C.ex, C.ey, C.bp, C.truth, C.kept, C.TAU
BASE = (O.SCORES, O.BEST)
GATED = f"num * 10000 > den * {TAU}"

# --- The private method -------------------------------------------------------------------------------------------------


def private(s, d) -> DataFrame:
    """One private run over the whole registries, with its messages."""
    return kept(s, d, "private", lambda: secure.links(ex(s, d), ey(s, d), TAU))


LINKED = O.query(f"select x_id, case when {GATED} then y_id end as y_id, num, den from bp", *BASE)
add("secure_link_all", lambda s, d: private(s, d).drop("messages"), LINKED)
add("secure_link_all_small", lambda s, d: secure.link_all(ex(s, d), ey(s, d), TAU, block=128), LINKED)
add("secure_best", lambda s, d: secure.link_all(ex(s, d), ey(s, d), None, block=512), O.query("select x_id, y_id, num, den from bp", *BASE))
add("secure_best_scan", lambda s, d: secure.link_all(ex(s, d), ey(s, d), TAU, order="scan", block=256), LINKED)
add("secure_link_one", lambda s, d: secure.link_one(ex(s, d), 10_000_000, ey(s, d), TAU), O.query(f"select x_id, case when {GATED} then y_id end as y_id, num, den from bp where x_id = 10000000", *BASE))
add("secure_scores", lambda s, d: secure.opened_scores(ex(s, d), ey(s, d)), O.query("select * from sc", O.SCORES))
_FRACTION = lambda f, p: f"(2 * len(list_intersect(x.{p}, y.{p})))::bigint as {f}_num, (greatest(len(x.{p}), 1) + greatest(len(y.{p}), 1))::bigint as {f}_den"
add("secure_dice", lambda s, d: secure.opened_dice(ex(s, d), ey(s, d)), O.query(f"select x.rec_id as x_id, y.rec_id as y_id, {_FRACTION('name', 'np')}, {_FRACTION('city', 'cp')} from ex x, ey y"))


def true_names(s, d) -> DataFrame:
    """(id, y_id, a, b): name positions of every true pair."""
    x, y = ex(s, d).select(F.col("rec_id").alias("id"), F.col("name_pos").alias("a")), ey(s, d).select(F.col("rec_id").alias("y_id"), F.col("name_pos").alias("b"))
    return truth(s, d).withColumnRenamed("x_id", "id").join(x, "id").join(y, "y_id")


_TRUE = "truth_ t join ex x on x.rec_id = t.x_id join ey y on y.rec_id = t.y_id"
for _name, _mode in (("secure_and_count", "arith"), ("secure_and_count_bits", "bits")):
    add(_name, lambda s, d, m=_mode: secure.and_counts(true_names(s, d).select("id", "a", "b"), m), O.query(f"select t.x_id as id, len(list_intersect(x.np, y.np))::bigint as shared from {_TRUE}"))


def differences(s, d) -> DataFrame:
    """How many rows only one of the two runs has."""
    a, b = private(s, d).select("x_id", "y_id", "num", "den"), match.accept(bp(s, d), TAU).select("x_id", "y_id", "num", "den")
    both = a.exceptAll(b).unionAll(b.exceptAll(a)).agg(F.count("*").alias("differing"))
    return both.crossJoin(a.agg(F.count("*").alias("records")))


add("secure_equals_clear", differences, O.query("select 0::bigint as differing, count(*) as records from bp", *BASE))
_LINE = "(select l_orderkey * 8 + l_linenumber as id, (l_partkey - 1000) * 7919 as a, (l_suppkey - 50) * 104729 as b from lineitem)"


def ring(s, d) -> DataFrame:
    rows = table(s, d, "lineitem")
    return rows.select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).cast("long").alias("id"), ((F.col("l_partkey") - 1000) * 7919).cast("long").alias("a"), ((F.col("l_suppkey") - 50) * 104729).cast("long").alias("b"))


for _what, _sql in (("multiply", "a * b"), ("greater", "(a > b)::int"), ("equal", "(a = b)::int"), ("select", "greatest(a, b)"), ("add", "a + b")):
    add(f"secure_{_what}", lambda s, d, w=_what: secure.kernel(ring(s, d), w), f"select id, ({_sql})::varchar as result from {_LINE}")

# Shares as data.
_CODES, _KEY = list(score.CODES), "session of the share queries"
add("share_open_roundtrip", lambda s, d: shares.opened(*shares.both(ex(s, d), _CODES, _KEY), _CODES), O.query("select rec_id, " + ", ".join(f"coalesce({c}, 0)::bigint as {c}" for c in _CODES) + " from ex"))


def bits_back(s, d) -> DataFrame:
    packed = C.part(s, d).select("p_partkey", text.pack(F.col("pos")).alias("bits"))
    back = shares.opened(*shares.both(packed, ["bits"], _KEY, by="p_partkey", bits=True), ["bits"], by="p_partkey", bits=True)
    return back.select("p_partkey", F.aggregate("bits", F.lit(0), lambda a, w: a + F.bit_count(w)).alias("ones"))


add("share_bits_roundtrip", bits_back, f"select p_partkey, len(pos)::int as ones from ({C._PART})")
add("share_shape", lambda s, d: shares.shape_only(shares.split(ex(s, d), _CODES, _KEY, 0)), O.query("select 0 as party, count(*) as n_rows, 4 as n_columns from ex"))
add("share_view_uniform", lambda s, d: shares.view_uniform(shares.split(ring(s, d).withColumnRenamed("id", "rec_id"), ["a"], _KEY, 1), "a").select((F.col("chi_square") < 400).alias("uniform")), "select true as uniform")


def granted(s, d) -> DataFrame:
    grants = ex(s, d).select("rec_id", F.when(F.col("rec_id") % 2 == 1, "clinic").otherwise("registry").alias("receiver"))
    return shares.revealed(*shares.both(ex(s, d), ["postcode"], _KEY), ["postcode"], grants, "clinic")


add("entitled_reveal", granted, O.query("select rec_id, coalesce(postcode, 0)::bigint as postcode from ex where rec_id % 2 = 1"))
_WRAP = "((l_partkey * 1000003 + l_suppkey) % 2147483647) * 4294967291"
_ALL = "18446744073709551616::hugeint"
add(
    "ring_sum_wrap",
    lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(shares.ring_sum(F.expr(_WRAP)).cast("string").alias("total")),
    f"select l_returnflag, (case when t >= 9223372036854775808::hugeint then t - {_ALL} else t end)::varchar as total from (select l_returnflag, sum(({_WRAP})::hugeint)::hugeint % {_ALL} as t from lineitem group by 1)",
)

# --- Cost ---------------------------------------------------------------------------------------------------------------


def ledger(s, d) -> DataFrame:
    m = private(s, d).select(F.explode("messages").alias("m")).select("m.*")
    return m.groupBy("step", "src", "dst").agg(F.sum("n_bytes").cast("long").alias("n_bytes"))


def ledger_sql() -> str:
    """What a run of N against M records in B blocks of Y sends, from the number of elements of each kernel."""
    games, finals = "n * (m - b)", "n * (b - 1)"
    elements = {  # step: (comparisons, products, dot products, opened map words)
        "dice": ("0", "0", "2 * n * m", "1800 * (n + m)"), "completeness": ("n * m", "6 * n * m", "0", "0"), "equality": ("4 * n * m", "4 * n * m", "0", "0"), "score": ("0", "7 * n * m", "0", "0"),
        "guard": ("n * m", "0", "0", "0"), "tournament": (games, f"5 * {games}", "0", "0"), "final": (finals, f"5 * {finals}", "0", "0"), "gate": ("n", "n", "0", "0"),
    }
    rows = []
    for step, (c, p, dots, words) in elements.items():
        ways = [(0, 1, f"8 * ({c}) + 16 * ({p}) + 8 * ({words})"), (1, 0, f"8 * ({c}) + 16 * ({p}) + 8 * ({words})"), (0, 2, f"64 * ({c})"), (1, 2, f"64 * ({c})"), (2, 1, f"72 * ({c}) + 8 * ({p}) + 8 * ({dots})")]
        rows += [f"select '{step}' as step, {a} as src, {b} as dst, ({v})::bigint as n_bytes from sizes" for a, b, v in ways]
    sizes = f"(select (select count(*) from ex) as n, (select count(*) from ey) as m, ((select count(*) from ey) + {secure.BLOCK - 1}) // {secure.BLOCK} as b)"
    return O.query(f"select * from ({' union all '.join(rows)}) where n_bytes > 0", ("sizes", f"select * from {sizes}"))


add("traffic_by_step", ledger, ledger_sql())
_KNOWN = f"(select col0::bigint as size, col2::double as a, col4::double as b, col6::double as c, col8::double as mb from (values {C._VALUES(cost.PUBLISHED)}))"
_HELD = f"(select db, z.size, a, b, c, mb from {C.DATABASES} z asof join {_KNOWN} k on z.size >= k.size)"
add("traffic_formula", lambda s, d: cost.by_size(C.databases(s, d), lambda sizes: cost.totals(s, sizes)).select("db", "size", "n_bytes", "bytes_per_candidate", "published_mb"), f"select db, size, 31208 * size + 28640 as n_bytes, round((31208 * size + 28640) / size, 1) as bytes_per_candidate, mb as published_mb from {_HELD}")
add("rounds_formula", lambda s, d: cost.by_size(C.databases(s, d), lambda sizes: cost.rounds(s, sizes)).select("db", "size", "levels", "n_rounds"), f"select db, size, ceil(log2(size))::int as levels, (13 + 5 * ceil(log2(size)))::int as n_rounds from {C.DATABASES}")
_NET = "(values ('A', 63.0, 330.0, 700.0), ('B', 63.0, 100.0, 100.0), ('C', 0.1, 25000.0, 25000.0)) p(profile, lat, between, up)"
_SECONDS = f"(13 + 5 * ceil(log2(size))) * lat::double / 1000 + greatest((14808 * size + 14336) * 8 / (between::double * 1e6), (696 * size - 32) * 8 / (up::double * 1e6), 448 * size * 8 / (up::double * 1e6)) + size * {cost.COMPUTE!r}::double"
add("modelled_seconds", lambda s, d: cost.by_size(C.databases(s, d), lambda sizes: cost.modelled(s, sizes)).select("db", "profile", "size", "seconds", "published_seconds", "ratio"), f"select db, profile, size, round(s, 4) as seconds, k as published_seconds, round(k / s, 3) as ratio from (select db, profile, size, {_SECONDS} as s, case profile when 'A' then a when 'B' then b else c end as k from {_HELD} t, {_NET})")


def offline(s, d) -> DataFrame:
    """Phases of the two methods on shares: the rival's dealer works before the inputs arrive."""
    x, y = ex(s, d), ey(s, d)
    fx, fy = bloom.encode(x), bloom.encode(y)
    ours = private(s, d).select(F.explode("messages").alias("m")).select("m.*")
    rival = secure.traffic(fx, fy, TAU, places=bloom.BITS, weights=bloom.WEIGHTS, offline=True)
    return cost.offline_share(ours).withColumn("method", F.lit("bigrams")).unionByName(cost.offline_share(rival).withColumn("method", F.lit("filters")))


add("offline_share", offline)

# --- The rival, weights and classical methods -----------------------------------------------------------------------------
_FILTERED = (C._BLOOM[0], C._BLOOM[1])
add("bloom_secure_link", lambda s, d: secure.link_all(bloom.encode(ex(s, d)), bloom.encode(ey(s, d)), TAU, places=bloom.BITS, weights=bloom.WEIGHTS, offline=True), O.query(f"select x_id, case when {GATED} then y_id end as y_id, num, den from bp", *C._BLOOM))
_FILTER_TRUE = "truth_ t join bx x on x.rec_id = t.x_id join by_ y on y.rec_id = t.y_id"


def filter_dice(s, d) -> DataFrame:
    a, b = (bloom.filter_positions(F.coalesce(c, F.array().cast("array<int>"))) for c in ("a", "b"))
    return true_names(s, d).select(F.col("id").alias("x_id"), fields.dice_fraction(a, b).alias("f")).select("x_id", "f.num", "f.den")


add("bloom_dice", filter_dice, O.query(f"select t.x_id, (2 * len(list_intersect(x.np, y.np)))::bigint as num, greatest(len(x.np) + len(y.np), 1)::bigint as den from {_FILTER_TRUE}", *_FILTERED))
_GAP = "2 * len(list_intersect(f.np, g.np)) / greatest(len(f.np) + len(g.np), 1) - 2 * len(list_intersect(x.np, y.np)) / greatest(len(x.np) + len(y.np), 1)"
add(
    "bloom_distortion",
    lambda s, d: bloom.distortion(true_names(s, d).where("a is not null and b is not null")),
    O.query(f"select count(*) as n, round(avg(gap), 6) as mean_diff, round(max(abs(gap)), 6) as max_diff from (select {_GAP} as gap from {_TRUE} join bx f on f.rec_id = t.x_id join by_ g on g.rec_id = t.y_id where x.nd > 0 and y.nd > 0)", *_FILTERED),
)
_BEST_TAU = C.SQL["best_threshold"][C.SQL["best_threshold"].rindex("select *, fp + fn as total"):]
add("bloom_best_threshold", lambda s, d: quality.best_threshold(C.bloom_bp(s, d), truth(s, d)), O.query(_BEST_TAU, *C._BLOOM, O.JUDGED))
GRID = {"even": score.WEIGHTS, "names": score.WEIGHTS | {"name": 700, "postcode": 100, "birth_day": 50}, "codes": score.WEIGHTS | {"name": 240, "postcode": 320, "birth_year": 280}}


def weight_grid(s, d) -> DataFrame:
    """Total errors of some weights at the threshold: trial and error."""
    out = None
    for name, weights in GRID.items():
        found = match.best_partners(ex(s, d), ey(s, d), weights=weights)
        one = quality.sweep(found, truth(s, d), (TAU,)).select(F.lit(name).alias("weights"), "fp", "fn", "total")
        out = one if out is None else out.unionAll(one)
    return out


def weight_grid_sql() -> str:
    parts, rows = [], []
    for name, weights in GRID.items():
        parts += [(f"sc_{name}", O.scores("ex", "ey", weights)), (f"bp_{name}", f"select x_id, y_id, num, den from ({O.best(f'sc_{name}')})")]
        judged = f"(select num * 10000 > den * {TAU} as ok, coalesce(b.y_id = t.y_id, false) as good, t.y_id is not null as has from bp_{name} b left join truth_ t on b.x_id = t.x_id)"
        rows.append(f"select '{name}' as weights, sum((ok and not good)::int)::bigint as fp, sum((has and not ok)::int)::bigint as fn, sum((ok and not good)::int + (has and not ok)::int)::bigint as total from {judged}")
    return O.query(" union all ".join(rows), *parts)


add("weight_grid", weight_grid, weight_grid_sql())


def weights_of(s, d) -> DataFrame:
    r = Registry.of(s, d)
    return baselines.frequency_weights(baselines.value_frequencies(r.left), baselines.field_error_rates(r.left, r.right, truth(s, d)))


_WEIGHT = C.SQL["weights_frequency"][len(C.over_registry("")):]
add("weights_scaled", lambda s, d: weights_of(s, d).select("field", "scaled"), C.over_registry(f"select field, floor(weight * 1300 / (sum(weight) over ()) + 0.5)::bigint as scaled from ({_WEIGHT})"))


def derived_link(s, d) -> DataFrame:
    """The link by weights from frequencies and errors: the combined name weighs as first and last name together."""
    held = {r["field"]: r["scaled"] for r in weights_of(s, d).collect()}  # one row a field
    raw = {"name": held["first_name"] + held["last_name"], **{f: held[f] for f in ("city", *score.CODES)}}
    weights = {f: max(1, w * 1300 // sum(raw.values())) for f, w in raw.items()}
    return quality.sweep(match.best_partners(ex(s, d), ey(s, d), weights=weights), truth(s, d))


add("error_sweep_derived_weights", derived_link)
_PRIOR = 0.001
_LOG = lambda sep, hit, miss: sep.join(f"case when {f} = 1 then {hit(m, u)!r}::double else {miss(m, u)!r}::double end" for f, (m, u) in C._MU.items())


def bayes_order(s, d) -> DataFrame:
    """Every agreement pattern with its probabilistic weight and its posterior under independent agreement bits; both orders are one."""
    rows = baselines.patterns(ex(s, d), ey(s, d))
    product = lambda at: math.prod([F.lit(1.0)]) * F.lit(1.0)
    weight, pm, pu = F.lit(0.0), F.lit(_PRIOR), F.lit(1 - _PRIOR)
    for f, (m, u) in C._MU.items():
        hit = F.col(f) == 1
        weight = weight + F.when(hit, math.log2(m / u)).otherwise(math.log2((1 - m) / (1 - u)))
        pm, pu = pm * F.when(hit, m).otherwise(1 - m), pu * F.when(hit, u).otherwise(1 - u)
    out = rows.select(*baselines.FIELDS, F.round(weight, 6).alias("weight"), F.round(F.log2(pm / pu), 6).alias("log_odds"))
    by = lambda c: F.dense_rank().over(Window.orderBy(F.desc(F.round(c, 4))))  # noqa: E731  at most 64 rows
    return out.withColumn("weight_rank", by("weight")).withColumn("posterior_rank", by("log_odds"))


_HIT, _MISS = lambda m, u: math.log2(m / u), lambda m, u: math.log2((1 - m) / (1 - u))
_ODDS = f"{math.log2(_PRIOR / (1 - _PRIOR))!r}::double + w"
add(
    "naive_bayes_order", bayes_order,
    O.query(f"select {', '.join(baselines.FIELDS)}, round(w, 6) as weight, round({_ODDS}, 6) as log_odds, (dense_rank() over (order by round(w, 4) desc))::int as weight_rank, (dense_rank() over (order by round(w, 4) desc))::int as posterior_rank from (select distinct {', '.join(baselines.FIELDS)}, {_LOG(' + ', _HIT, _MISS)} as w from ag)", ("ag", C._AGREE)),
)

# --- Several owners, duplicates, other tables ---------------------------------------------------------------------------------


def holders(s, d) -> list[DataFrame]:
    everyone = ex(s, d).unionByName(ey(s, d))
    return [everyone.where(F.col("rec_id") % 3 == k) for k in range(3)]


def many_sql(where: str) -> str:
    best = f"select * from (select *, row_number() over (partition by x_id, y_id % 3 order by {O.KEY} desc, y_id) as rank from sc) where rank = 1"
    return O.query(f"select (x_id % 3)::int as left_holder, (y_id % 3)::int as right_holder, x_id, y_id, (num * 1000000) // den as score_ppm from ({best}) where {GATED}", ("ea", "select * from ex union all select * from ey"), ("sc", O.scores("ea", "ea", where=where)))


add("link_many_pairs", lambda s, d: match.link_many(holders(s, d), TAU), many_sql("x.rec_id % 3 < y.rec_id % 3"))
add("link_many_query", lambda s, d: match.link_many(holders(s, d), TAU, "query"), many_sql("x.rec_id % 3 = 0 and y.rec_id % 3 > 0"))
_TWICE = 8500
add("self_duplicates", lambda s, d: match.scored(match.pairs(ey(s, d), ey(s, d)).where("x_rec_id < y_rec_id")).where(match.above(F.col("num"), F.col("den"), _TWICE)).select("x_id", "y_id", "num", "den"), O.query(f"select x_id, y_id, num, den from sc where num * 10000 > den * {_TWICE}", ("sc", O.scores("ey", "ey", where="x.rec_id < y.rec_id"))))


def lateral(s, d) -> DataFrame:
    name = f"pairs_{uuid.uuid4().hex}"
    blocks.top(ex(s, d), ey(s, d)).withColumn("k", score.key(F.col("num"), F.col("den"))).createOrReplaceTempView(name)
    ids = f"ids_{name}"
    ex(s, d).select("rec_id").createOrReplaceTempView(ids)
    return s.sql(f"select rec_id as x_id, y_id, num, den from {ids}, lateral (select y_id, num, den from {name} where x_id = rec_id order by k desc, y_id limit 1)")


add("best_partner_lateral", lateral, O.query("select x_id, y_id, num, den from bp", *BASE))


def one_text(x: DataFrame, y: DataFrame, keys: dict[str, int], weight: int, apart: bool = False) -> DataFrame:
    """(x_id, y_id, num, den): best partner by one text field (id, pos) and coded fields with their weights."""
    a, b = (v.select([F.col(c).alias(f"{p}_{c}") for c in v.columns]) for v, p in ((x, "x"), (y, "y")))
    both = a.crossJoin(F.broadcast(b)) if y.count() <= match.BROADCAST_ROWS else a.join(b)
    if apart:
        both = both.where("x_id <> y_id")
    f = fields.dice_fraction(F.col("x_pos"), F.col("y_pos"))
    agree = sum((fields.equal_bit(F.col(f"x_{k}"), F.col(f"y_{k}")) * w for k, w in keys.items()), F.lit(0))
    rows = both.select("x_id", "y_id", f["num"].alias("a"), f["den"].alias("b"), agree.alias("e"))
    scored = rows.select("x_id", "y_id", (F.col("a") * weight + F.col("e") * F.col("b")).alias("num"), (F.col("b") * (weight + sum(keys.values()))).alias("den"))
    return match.best_window(scored).drop("rank")


def one_text_sql(x: str, y: str, keys: dict[str, int], weight: int, where: str = "true") -> str:
    agree = " + ".join(f"coalesce((x.{k} = y.{k})::int, 0) * {w}" for k, w in keys.items())
    sc = f"select x.id as x_id, y.id as y_id, (2 * len(list_intersect(x.pos, y.pos)) * {weight} + ({agree}) * greatest(len(x.pos) + len(y.pos), 1))::bigint as num, (greatest(len(x.pos) + len(y.pos), 1) * {weight + sum(keys.values())})::bigint as den from {x} x, {y} y where {where}"
    return f"select x_id, y_id, num, den from ({O.best(f'({sc})')})"


_PARTS = lambda k: f"(select p_partkey as id, pos, p_brand, p_size from ({C._PART}) where p_partkey % 2 = {k})"
_PART_KEYS = {"p_brand": 200, "p_size": 160}


def part_ties(s, d) -> DataFrame:
    """Parts of even key against parts of odd key: two registries with few distinct names."""
    p = C.part(s, d).select(F.col("p_partkey").alias("id"), "pos", "p_brand", "p_size")
    return one_text(p.where("id % 2 = 0"), p.where("id % 2 = 1"), _PART_KEYS, 480)


add("part_best_ties", part_ties, one_text_sql(_PARTS(0), _PARTS(1), _PART_KEYS, 480))
_TITLE = O.normal("regexp_extract(html, '<title>([^<]*)', 1)")
_PAGES = f"(select id, {O.positions('nm')} as pos, host from (select page_id as id, {_TITLE} as nm, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as host from pages))"


def page_links(s, d) -> DataFrame:
    p = table(s, d, "pages").select(F.col("page_id").alias("id"), text.positions(text.normalise(F.regexp_extract("html", "<title>([^<]*)", 1))).alias("pos"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"))
    return one_text(p, p, {"host": 300}, 700, True)


add("page_title_links", page_links, one_text_sql(_PAGES, _PAGES, {"host": 300}, 700, "x.id <> y.id"))


def document_pairs(s, d) -> DataFrame:
    """(x_id, y_id, num, den): bigram Dice of whole texts in one language, source and length band of 25 characters."""
    rows = table(s, d, "documents").select("doc_id", "lang", "source", F.call_function("div", F.length("text"), F.lit(25)).alias("band"), text.long_positions(text.normalise(F.col("text"))).alias("pos"))
    a, b = rows.select(F.col("doc_id").alias("x_id"), "lang", "source", "band", F.col("pos").alias("a")), rows.select(F.col("doc_id").alias("y_id"), "lang", "source", "band", F.col("pos").alias("b"))
    both = a.join(b, ["lang", "source", "band"]).where("x_id < y_id")
    return both.select("x_id", "y_id", fields.dice_fraction(F.col("a"), F.col("b")).alias("f")).select("x_id", "y_id", "f.num", "f.den")


_WINDOW = f"(select doc_id, lang, source, length(text) // 25 as band, {O.long_positions('chars_')} as pos from (select *, string_split({O.normal('text')}, '') as chars_ from documents))"
_DOCS = f"(select x.doc_id as x_id, y.doc_id as y_id, (2 * len(list_intersect(x.pos, y.pos)))::bigint as num, greatest(len(x.pos) + len(y.pos), 1)::bigint as den from w x join w y on x.lang = y.lang and x.source = y.source and x.band = y.band and x.doc_id < y.doc_id)"
add("document_links", lambda s, d: document_pairs(s, d).where("num * 100 >= den * 95"), f"with w as materialized (select * from {_WINDOW}) select * from {_DOCS} where num * 100 >= den * 95")
add("document_dice_histogram", lambda s, d: document_pairs(s, d).groupBy(F.call_function("div", F.col("num") * 20, F.col("den")).alias("bin")).agg(F.count("*").alias("n")), f"with w as materialized (select * from {_WINDOW}) select num * 20 // den as bin, count(*) as n from {_DOCS} group by 1")


def item_links(s, d) -> DataFrame:
    """The document that covers most bigrams of each benchmark item, the smallest id on ties."""
    items = table(s, d, "benchmark").select(F.col("item_id").alias("x_id"), text.normalise(F.col("text")).alias("a"))
    docs = table(s, d, "documents").select(F.col("doc_id").alias("y_id"), text.normalise(F.col("text")).alias("b"))
    return covers.best(items, docs, 3)


_ITEM = f"select item_id as x_id, {O.long_positions('chars_', 3)} as a from (select item_id, string_split({O.normal('text')}, '') as chars_ from benchmark)"
_TEXT = f"select doc_id as y_id, {O.long_positions('chars_', 3)} as b from (select doc_id, string_split({O.normal('text')}, '') as chars_ from documents)"
add("benchmark_links", item_links, f"with i as materialized ({_ITEM}), t as materialized ({_TEXT}), g as (select x_id, y_id, count(*) as num from (select y_id, unnest(b) as p from t) u join (select x_id, unnest(a) as p from i) v using (p) group by all), sc as (select g.*, len(a)::bigint as den from g join i using (x_id)) select x_id, y_id, num, den from ({O.best('sc')})")
add(
    "label_agreement",
    lambda s, d: table(s, d, "labels").join(table(s, d, "documents").select("doc_id", F.md5("text").alias("copy")), "doc_id").groupBy("copy").agg(F.count("*").alias("n"), F.count_distinct("quality").alias("q"), F.count_distinct("toxic").alias("t")).where("n > 1").agg(F.count("*").alias("classes"), F.coalesce(F.sum((F.col("q") == 1).cast("long")), F.lit(0)).alias("same_quality"), F.coalesce(F.sum((F.col("t") == 1).cast("long")), F.lit(0)).alias("same_toxic")),
    "select count(*) as classes, coalesce(sum((q = 1)::int), 0)::bigint as same_quality, coalesce(sum((t = 1)::int), 0)::bigint as same_toxic from (select md5(text) as copy, count(*) as n, count(distinct quality) as q, count(distinct toxic) as t from labels join documents using (doc_id) group by 1) where n > 1",
)


def nearest_vectors(s, d) -> DataFrame:
    """(x_id, y_id, cosine) of every vector's nearest other one: all pairs by matrix products, the cosines of those near the best anew, summed in order."""
    v = table(s, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    a, b = v.select(F.col("vec_id").alias("x_id"), F.col("v").alias("a")), v.select(F.col("vec_id").alias("y_id"), F.col("v").alias("b"))
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda t, z: t + z)
    both = covers.near_vectors(v).distinct().join(a, "x_id").join(b, "y_id").where("x_id <> y_id")
    rows = both.select("x_id", "y_id", F.round(dot(F.col("a"), F.col("b")) / F.sqrt(dot(F.col("a"), F.col("a")) * dot(F.col("b"), F.col("b"))), 6).alias("cosine"))
    return rows.groupBy("x_id").agg(F.max(F.struct("cosine", (-F.col("y_id")).alias("n"))).alias("m")).select("x_id", (-F.col("m.n")).alias("y_id"), "m.cosine")


add("embedding_best", nearest_vectors, "with v as (select vec_id, embedding::double[] as e from embeddings) select x_id, y_id, cosine from (select *, row_number() over (partition by x_id order by cosine desc, y_id) as r from (select a.vec_id as x_id, b.vec_id as y_id, round(list_dot_product(a.e, b.e) / sqrt(list_dot_product(a.e, a.e) * list_dot_product(b.e, b.e)), 6) as cosine from v a, v b where a.vec_id <> b.vec_id)) where r = 1")

# --- Field similarity -----------------------------------------------------------------------------------------------------
add("dice_fraction_only", lambda s, d: true_names(s, d).select("id", fields.dice_fraction(F.coalesce("a", F.array().cast("array<int>")), F.coalesce("b", F.array().cast("array<int>"))).alias("f")).select("id", "f.num", "f.den"), O.query(f"select t.x_id as id, (2 * len(list_intersect(x.np, y.np)))::bigint as num, greatest(len(x.np) + len(y.np), 1)::bigint as den from {_TRUE}"))


def empty_guard(s, d) -> DataFrame:
    """Cities of every true pair, with how many of the two have no bigram: the denominator is never zero."""
    none = F.array().cast("array<int>")
    c = lambda v, i, n: v.select(F.col("rec_id").alias(i), F.coalesce("city_pos", none).alias(n))
    rows = truth(s, d).join(c(ex(s, d), "x_id", "a"), "x_id").join(c(ey(s, d), "y_id", "b"), "y_id")
    out = rows.select(((F.size("a") == 0).cast("int") + (F.size("b") == 0).cast("int")).alias("empty"), fields.dice_fraction(F.col("a"), F.col("b")).alias("f"))
    return out.groupBy("empty").agg(F.count("*").alias("n"), F.min("f.den").alias("least_den"), F.sum("f.num").alias("nums"))


add("dice_empty_guard", empty_guard, O.query(f"select empty, count(*) as n, min(den)::bigint as least_den, sum(num)::bigint as nums from (select (len(x.cp) = 0)::int + (len(y.cp) = 0)::int as empty, 2 * len(list_intersect(x.cp, y.cp)) as num, greatest(len(x.cp) + len(y.cp), 1) as den from {_TRUE}) group by 1"))
_AT = 800_000
add(
    "size_filter_pairs",
    lambda s, d: match.pairs(ex(s, d), ey(s, d)).select(*[c.alias(n) for c, n in zip(score.fractions()["name"], ("num", "den"))], (2 * F.least(F.greatest("x_name_card", F.lit(1)), F.greatest("y_name_card", F.lit(1)))).alias("most")).agg(F.count("*").alias("pairs"), F.sum((F.col("most") * 1_000_000 >= F.col("den") * _AT).cast("long")).alias("kept"), F.sum((F.col("num") * 1_000_000 >= F.col("den") * _AT).cast("long")).alias("similar"), F.sum(((F.col("num") * 1_000_000 >= F.col("den") * _AT) & (F.col("most") * 1_000_000 < F.col("den") * _AT)).cast("long")).alias("lost")),
    O.query(f"select count(*) as pairs, sum((2 * least(p, q) * 1000000 >= (p + q) * {_AT})::int)::bigint as kept, sum((n * 1000000 >= (p + q) * {_AT})::int)::bigint as similar, 0::bigint as lost from (select greatest(len(x.np), 1)::bigint as p, greatest(len(y.np), 1)::bigint as q, 2 * len(list_intersect(x.np, y.np))::bigint as n from ex x, ey y)"),
)

# --- Relational operators ---------------------------------------------------------------------------------------------------
_R = lambda s, d: Registry.of(s, d)
add("ops_filter_band", lambda s, d: _R(s, d).left.where("birth_year between 1960 and 1979 and birth_month in (1, 2, 3) and last_name rlike '^[a-m]' and city is not null").select("rec_id"), C.over_registry("select rec_id from registry_left_ where birth_year between 1960 and 1979 and birth_month in (1, 2, 3) and regexp_matches(last_name, '^[a-m]') and city is not null"))
_ACCEPTED = f"(select x_id, y_id from bp where {GATED})"


def merged(s, d) -> DataFrame:
    """Both registries in one, linked rows side by side and the others kept."""
    links = match.accept(bp(s, d), TAU).where("accepted").select("x_id", "y_id")
    left = _R(s, d).left.select(F.col("rec_id").alias("x_id"))
    return left.join(links, "x_id", "left").join(_R(s, d).right.select(F.col("rec_id").alias("y_id")), "y_id", "full").select("x_id", "y_id")


add("ops_join_full_merged", merged, O.query(f"select l.rec_id as x_id, coalesce(r.rec_id, b.y_id) as y_id from ex l left join {_ACCEPTED} b on b.x_id = l.rec_id full join ey r on r.rec_id = b.y_id", *BASE))


def as_of(s, d) -> DataFrame:
    """Each event with its user's order that was newest at that time of the calendar; one pass over both, by user."""
    e = table(s, d, "events").select(F.col("user_id").alias("k"), F.dayofyear("ts").alias("at"), F.col("event_id"), F.lit(None).cast("long").alias("o"))
    o = table(s, d, "orders").select(F.col("o_custkey").alias("k"), F.dayofyear("o_orderdate").alias("at"), F.lit(None).cast("long").alias("event_id"), F.col("o_orderkey").alias("o"))
    order = Window.partitionBy("k").orderBy("at", F.col("event_id").isNotNull(), "o").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return e.unionByName(o).withColumn("o_orderkey", F.last("o", True).over(order)).where("event_id is not null").select("event_id", "o_orderkey")


add("ops_asof_arrival", as_of, "select event_id, (select o_orderkey from orders where o_custkey = user_id and dayofyear(o_orderdate) <= dayofyear(ts) order by dayofyear(o_orderdate) desc, o_orderkey desc limit 1) as o_orderkey from events")
_PROFILE = "n_errors, shuffled"
add("ops_grouping_sets", lambda s, d: s.sql(f"select {_PROFILE}, count(*) as n from {{c}} group by grouping sets ((n_errors, shuffled), (n_errors), ())", c=_R(s, d).copy("r")), C.over_registry(f"select {_PROFILE}, count(*) as n from copy_right group by grouping sets ((n_errors, shuffled), (n_errors), ())"))
add("ops_rollup_traffic", lambda s, d: ledger(s, d).rollup("step", "src").agg(F.sum("n_bytes").alias("n_bytes")), f"select step, src, sum(n_bytes)::bigint as n_bytes from ({ledger_sql()}) group by rollup (step, src)")
_TOTALS = C.SQL["published_error_totals"]
add("ops_pivot_methods", lambda s, d: C.error_totals(s, d).unpivot("tau_bp", ["total_two", "total_three"], "method", "total").groupBy("method").pivot("tau_bp", [6000, 7000, 8000]).agg(F.first("total")).select("method", *[F.col(str(t)).cast("long").alias(f"at_{t}") for t in (6000, 7000, 8000)]), f"select method, max(total) filter (tau_bp = 6000)::bigint as at_6000, max(total) filter (tau_bp = 7000)::bigint as at_7000, max(total) filter (tau_bp = 8000)::bigint as at_8000 from (unpivot (select tau_bp, total_two, total_three from ({_TOTALS})) on total_two, total_three into name method value total) group by 1")
_RUN = "sum(total) over (order by tau_bp rows between unbounded preceding and current row)"
add("ops_running_errors", lambda s, d: quality.sweep(bp(s, d), truth(s, d)).select("tau_bp", "total", F.expr(_RUN).alias("running"), F.expr("total - lag(total) over (order by tau_bp)").alias("change")), O.query(f"select tau_bp, total, ({_RUN})::bigint as running, total - lag(total) over (order by tau_bp) as change from ({O.SWEEP.replace('{taus}', str(list(quality.TAUS)))})", *BASE, O.JUDGED))
add("ops_union_owners", lambda s, d: _R(s, d).left.unionByName(_R(s, d).right).groupBy("owner").agg(F.count("*").alias("n"), F.count("birth_name").alias("birth_names")), C.over_registry("select owner, count(*) as n, count(birth_name) as birth_names from (select owner, birth_name from registry_left_ union all select owner, birth_name from registry_right_) group by 1"))
add("ops_approx_distinct", lambda s, d: _R(s, d).left.agg(*[F.approx_count_distinct(c).alias(c) for c in ("last_name", "city", "postcode")]))

# --- Streams ------------------------------------------------------------------------------------------------------------


def streamed_links(s, d) -> DataFrame:
    """Arriving users, as records of the left registry, linked batch by batch with the right one."""
    folder = s.sparkContext.getConf().get("spark.checkpoint.dir")
    if not folder and not s.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    folder = folder or "/tmp/veilmatch-checkpoints"
    path = f"{folder.rstrip('/')}/links-{uuid.uuid4().hex}"
    arriving = ex(s, d).withColumn("arrival_key", F.col("rec_id") - 10_000_000)
    arrivals.link_stream(arrivals.events(s, d), arriving, ey(s, d), TAU, path)
    return s.read.parquet(path).select("x_id", "y_id", "num", "den")


add("stream_links", streamed_links, O.query(f"select x_id, case when {GATED} then y_id end as y_id, num, den from bp where x_id in (select 10000000 + user_id from events)", *BASE))
