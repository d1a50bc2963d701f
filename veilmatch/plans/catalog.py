"""Registered queries of the linkage engine and their SQL."""

from __future__ import annotations

from veilmatch.operators.registry import ATTRIBUTES, Registry, duck_views

VIEWS = duck_views()
QUERIES: dict = {}
SQL: dict[str, str] = {}


def over_registry(body: str) -> str:
    """DuckDB SQL over the derived registry."""
    return f"with {VIEWS} {body}"


_FIELDS = ", ".join(ATTRIBUTES)
QUERIES["name_frequency"] = lambda spark, d: Registry.of(spark, d).words
SQL["name_frequency"] = over_registry("select * from word_counts")
QUERIES["registry_original"] = lambda spark, d: Registry.of(spark, d).person
SQL["registry_original"] = over_registry("select * from person")
QUERIES["registry_corrupted"] = lambda spark, d: Registry.of(spark, d).copy("l")
SQL["registry_corrupted"] = over_registry("select * from copy_left")
QUERIES["registry_left"] = lambda spark, d: Registry.of(spark, d).left
SQL["registry_left"] = over_registry(f"select rec_id, owner, {_FIELDS} from registry_left_")
QUERIES["registry_right"] = lambda spark, d: Registry.of(spark, d).right
SQL["registry_right"] = over_registry(f"select rec_id, owner, {_FIELDS} from registry_right_")
QUERIES["truth_pairs"] = lambda spark, d: Registry.of(spark, d).truth
SQL["truth_pairs"] = over_registry("select * from truth_")

from pyspark.sql import functions as F  # noqa: E402

from veilmatch.operators import blocks, match, quality, score  # noqa: E402
from veilmatch.plans import oracle as O  # noqa: E402
from veilmatch.sources.tables import stored  # noqa: E402

_KEPT: dict[tuple, object] = {}
TAU = 7000


def kept(spark, d, name, build):
    """A frame that several queries read, made once for a folder and written."""
    key = (spark.sparkContext.applicationId, d, name)
    if key not in _KEPT:
        for old in [k for k in _KEPT if k[:2] != key[:2]]:
            del _KEPT[old]
        _KEPT[key] = stored(build())
    return _KEPT[key]


def ex(spark, d):
    return kept(spark, d, "ex", lambda: score.encode(Registry.of(spark, d).left))


def ey(spark, d):
    return kept(spark, d, "ey", lambda: score.encode(Registry.of(spark, d).right))


def truth(spark, d):
    return Registry.of(spark, d).truth


def bp(spark, d):
    return kept(spark, d, "bp", lambda: match.best_partners(ex(spark, d), ey(spark, d)))


def add(name, build, sql=None):
    QUERIES[name] = build
    if sql:
        SQL[name] = sql


_BASE = (O.SCORES, O.BEST)
_JUDGED = (*_BASE, O.JUDGED)
add("pair_scores", lambda s, d: match.scored(match.pairs(ex(s, d).where("rec_id < 10000020"), ey(s, d))), O.query("select * from sc", ("sc", O.scores("ex", "ey", where="x.rec_id < 10000020"))))
add("best_partner", lambda s, d: bp(s, d), O.query("select * from bp", *_BASE))
add("best_partner_grid", lambda s, d: match.best_partners(ex(s, d), ey(s, d), grid=(3, 4)), O.query("select * from bp", *_BASE))
add("best_partner_window", lambda s, d: match.best_window(blocks.top(ex(s, d), ey(s, d))).drop("rank"), O.query("select x_id, y_id, num, den from bp", *_BASE))
add("top3_partners", lambda s, d: match.best_window(blocks.top(ex(s, d), ey(s, d), 3), 3), O.query(O.best("sc", 3), O.SCORES))
add("accepted_links", lambda s, d: match.accept(bp(s, d), TAU).where("accepted").select("x_id", "y_id", "score_ppm"), O.query(f"select x_id, y_id, score_ppm from bp where num * 10000 > den * {TAU}", *_BASE))
add("accepted_links_non_strict", lambda s, d: match.accept(bp(s, d), 10000, False).where("accepted").select("x_id", "y_id"), O.query("select x_id, y_id from bp where num >= den", *_BASE))
add("link_all", lambda s, d: match.accept(bp(s, d), TAU), O.query(f"select x_id, case when num * 10000 > den * {TAU} then y_id end as y_id, num, den, score_ppm, num * 10000 > den * {TAU} as accepted from bp", *_BASE))
add("lossless_cover_links", lambda s, d: match.lossless_links(ex(s, d), ey(s, d), TAU).select("x_id", "y_id", "score_ppm"), SQL["accepted_links"])
add("error_sweep", lambda s, d: quality.sweep(bp(s, d), truth(s, d)), O.query(O.SWEEP.replace("{taus}", str(list(quality.TAUS))), *_JUDGED))
add("error_curve_fine", lambda s, d: quality.sweep(bp(s, d), truth(s, d), tuple(range(5000, 9000, 100))), O.query(O.SWEEP.replace("{taus}", "range(5000, 9000, 100)"), *_JUDGED))
add("error_counts", lambda s, d: quality.sweep(bp(s, d), truth(s, d), (TAU,)), O.query(O.SWEEP.replace("{taus}", f"[{TAU}]"), *_JUDGED))
add(
    "best_threshold",
    lambda s, d: quality.best_threshold(bp(s, d), truth(s, d)),
    O.query(
        "select *, fp + fn as total from (select t.tau_bp, (select count(*) from jd where not is_true and score_ppm // 100 > t.tau_bp)::bigint as fp, (select count(*) from jd where has_partner and score_ppm // 100 <= t.tau_bp)::bigint as fn from (select distinct (score_ppm // 100)::int as tau_bp from jd) t) order by total, tau_bp limit 1",
        *_JUDGED,
    ),
)
add("roc_auc", lambda s, d: quality.auc(bp(s, d), truth(s, d)), O.query("select round(sum(case when p.score_ppm > n.score_ppm then 1.0 when p.score_ppm = n.score_ppm then 0.5 else 0 end) / count(*), 6)::double as auc, count(distinct p.x_id)::bigint as positives, count(distinct n.x_id)::bigint as negatives from jd p, jd n where p.is_true and not n.is_true", *_JUDGED))
add("roc_points", lambda s, d: quality.roc(bp(s, d), truth(s, d)), O.query("select s.ppm, (select count(*) from jd where is_true and score_ppm >= s.ppm)::bigint as tp, (select count(*) from jd where not is_true and score_ppm >= s.ppm)::bigint as fp from (select distinct score_ppm as ppm from jd) s", *_JUDGED))
add("precision_recall", lambda s, d: quality.precision_recall(quality.sweep(bp(s, d), truth(s, d))), O.query(f"select tau_bp, round(tp / (tp + fp), 6) as precision, round(tp / (tp + fn), 6) as recall, round(2 * tp / (2 * tp + fp + fn), 6) as f1 from ({O.SWEEP.replace('{taus}', str(list(quality.TAUS)))})", *_JUDGED))

from veilmatch.operators import baselines, bloom  # noqa: E402

_BITS = f"list_sort(list_distinct(flatten(list_transform({{c}}, lambda p: list_transform(range({bloom.HASHES}), lambda i: ((('0x' || substr(md5(p::varchar), 1, 8))::bigint + i * ('0x' || substr(md5(p::varchar), 9, 8))::bigint) % {bloom.BITS})::int)))))"
_BLOOM = (
    ("bx", f"select * exclude (np, cp), {_BITS.format(c='np')} as np, {_BITS.format(c='cp')} as cp from ex"),
    ("by_", f"select * exclude (np, cp), {_BITS.format(c='np')} as np, {_BITS.format(c='cp')} as cp from ey"),
    ("sc", O.scores("bx", "by_", bloom.WEIGHTS)),
    O.BEST,
)


def bloom_bp(s, d):
    return kept(s, d, "bloom", lambda: bloom.best_partners(ex(s, d), ey(s, d)))


add("bloom_bits", lambda s, d: ex(s, d).select("rec_id", F.size(bloom.filter_positions(F.coalesce("name_pos", F.array().cast("array<int>")))).alias("bits")), O.query(f"select rec_id, len({_BITS.format(c='np')})::int as bits from ex"))
add("bloom_best_partner", lambda s, d: bloom_bp(s, d), O.query("select * from bp", *_BLOOM))
add("bloom_error_sweep", lambda s, d: quality.sweep(bloom_bp(s, d), truth(s, d)), O.query(O.SWEEP.replace("{taus}", str(list(quality.TAUS))), *_BLOOM, O.JUDGED))
add("bloom_roc_auc", lambda s, d: quality.auc(bloom_bp(s, d), truth(s, d)), O.query(SQL["roc_auc"][SQL["roc_auc"].rindex("select round(sum(case"):], *_BLOOM, O.JUDGED))
add("bloom_exposure", lambda s, d: bloom.exposure(ex(s, d)), O.query(f"select same, count(*) as filters from (select count(*) as same from (select {_BITS.format(c='np')} as f, nd from ex) where nd > 0 group by f) group by same"))
add("deterministic_links", lambda s, d: baselines.deterministic(Registry.of(s, d).left, Registry.of(s, d).right, ("last_name", "birth_year", "birth_month", "birth_day")), over_registry("select l.rec_id as x_id, r.rec_id as y_id from registry_left_ l join registry_right_ r on l.last_name = r.last_name and l.birth_year = r.birth_year and l.birth_month = r.birth_month and l.birth_day = r.birth_day"))
_AGREE = "select x.rec_id as x_id, y.rec_id as y_id, " + ", ".join(
    [f"(2 * len(list_intersect(x.{p}, y.{p})) * 1000000 >= (greatest(len(x.{p}), 1) + greatest(len(y.{p}), 1)) * 800000)::int as {f}" for f, p in (("name", "np"), ("city", "cp"))] + [f"coalesce((x.{f} = y.{f})::int, 0) as {f}" for f in score.CODES]
) + " from ex x, ey y"
add("agreement_patterns", lambda s, d: baselines.patterns(ex(s, d), ey(s, d)), O.query(f"select {', '.join(baselines.FIELDS)}, count(*) as n from ag group by all", ("ag", _AGREE)))
_MU = {"name": (0.8, 0.01), "city": (0.9, 0.02), "postcode": (0.9, 0.01), "birth_year": (0.9, 0.02), "birth_month": (0.9, 0.083), "birth_day": (0.9, 0.036)}
import math  # noqa: E402

_FS = " + ".join(f"case when {f} = 1 then {round(1000 * math.log2(m / u))} else {round(1000 * math.log2((1 - m) / (1 - u)))} end" for f, (m, u) in _MU.items())
add("fs_three_way", lambda s, d: baselines.fellegi(ex(s, d), ey(s, d), _MU, 0.0, 10.0).groupBy("decision").agg(F.count("*").alias("pairs"), F.max("weight").alias("top")), O.query(f"select decision, count(*) as pairs, max(weight)::bigint as top from (select weight, case when weight >= 10000 then 'link' when weight >= 0 then 'review' else 'no' end as decision from (select {_FS} as weight from ag)) group by 1", ("ag", _AGREE)))
add("fs_scores", lambda s, d: baselines.fellegi(ex(s, d), ey(s, d), _MU, 0.0, 10.0).where("weight >= 10000").select("x_id", "y_id", "weight"), O.query(f"select x_id, y_id, weight::bigint as weight from (select x_id, y_id, {_FS} as weight from ag) where weight >= 10000", ("ag", _AGREE)))


def _em(s, d):
    rows = [r.asDict() for r in baselines.patterns(ex(s, d), ey(s, d)).collect()]
    return s.createDataFrame([(f, round(m, 6), round(u, 6)) for f, (m, u) in baselines.em(rows).items()], "field string, m double, u double")


add("weights_em", _em)
for _kind in ("svm", "mlp", "forest", "boosted", "bayes"):
    add(f"ml_{_kind}", lambda s, d, k=_kind: baselines.learned(ex(s, d), ey(s, d), truth(s, d), k))
_UNPIVOT = " union all ".join(f"select '{c}' as field, x.{c}::varchar as x, y.{c}::varchar as y from truth_ t join registry_left_ x on x.rec_id = t.x_id join registry_right_ y on y.rec_id = t.y_id" for c in ATTRIBUTES)
_ERRORS = f"select field, count(*) as n, sum((x <> y)::int)::bigint as differ from ({_UNPIVOT}) where x is not null and y is not null group by field"
_FREQ = "select field, count(*) as distinct_values, round(sum(n::double * n) / (sum(n) * sum(n)), 6) as collision from (select field, v, count(*) as n from (" + " union all ".join(f"select '{c}' as field, {c}::varchar as v from registry_left_" for c in ATTRIBUTES) + ") where v is not null group by all) group by field"
add("field_error_rates", lambda s, d: baselines.field_error_rates(Registry.of(s, d).left, Registry.of(s, d).right, truth(s, d)), over_registry(_ERRORS))
add("weights_collision", lambda s, d: baselines.value_frequencies(Registry.of(s, d).left), over_registry(_FREQ))
add("weights_frequency", lambda s, d: baselines.frequency_weights(baselines.value_frequencies(Registry.of(s, d).left), baselines.field_error_rates(Registry.of(s, d).left, Registry.of(s, d).right, truth(s, d))).drop("scaled"), over_registry(f"select f.field, round(log2((1 - least(greatest(differ / n, 0.001), 0.999)) * distinct_values), 6) as weight from ({_FREQ}) f join ({_ERRORS}) e on f.field = e.field"))

from veilmatch.functions import fields, text  # noqa: E402
from veilmatch.operators import cost  # noqa: E402
from veilmatch.sources.tables import table  # noqa: E402
from veilmatch.streaming import arrivals  # noqa: E402

# Encoding, on native tables.
_P = "(select p_partkey, p_name, p_brand, p_size from part)"
_PART = f"select p_partkey, {O.positions('nm')} as pos, {O.positions('nm', 3)} as pos3, p_name, p_brand, p_size from (select *, {O.normal('p_name')} as nm from {_P})"


def part(s, d, dealt=False):
    """The parts with their positions; ``dealt`` over all cores where the work on a row is worth it, as the table is one small file."""
    rows = table(s, d, "part").select("p_partkey", "p_name", "p_brand", "p_size")
    if dealt:
        rows = rows.repartition(4 * s.sparkContext.defaultParallelism)
    return rows.select("*", text.positions(text.normalise(F.col("p_name"))).alias("pos"))


add("normalise_titles", lambda s, d: table(s, d, "pages").select("page_id", text.normalise(F.regexp_extract("html", "<title>([^<]*)", 1)).alias("title")), f"select page_id, {O.normal('''regexp_extract(html, '<title>([^<]*)', 1)''')} as title from pages")
add("normalise_accents", lambda s, d: table(s, d, "documents").where("lang <> 'en'").select("doc_id", F.md5(text.normalise(F.substring("text", 1, 500))).alias("digest")), f"select doc_id, md5({O.normal('substr(text, 1, 500)')}) as digest from documents where lang <> 'en'")
add("bigram_positions_part", lambda s, d: part(s, d).select("p_partkey", F.array_join("pos", ",").alias("pos")), f"select p_partkey, array_to_string(pos, ',') as pos from ({_PART})")
add("bigram_cardinality", lambda s, d: part(s, d).select("p_partkey", F.size("pos").alias("n")), f"select p_partkey, len(pos)::int as n from ({_PART})")
add("qgram3_positions", lambda s, d: part(s, d).select("p_partkey", F.array_join(text.positions(text.normalise(F.col("p_name")), 3), ",").alias("pos")), f"select p_partkey, array_to_string(pos3, ',') as pos from ({_PART})")
add("bigram_packed_words", lambda s, d: part(s, d).select("p_partkey", F.aggregate(text.pack(F.col("pos")), F.lit(0), lambda a, w: a + F.bit_count(w)).alias("ones"), F.bit_count(text.pack(F.col("pos"))[3]).alias("ones3")), f"select p_partkey, len(pos)::int as ones, len(list_filter(pos, lambda p: p // 64 = 3))::int as ones3 from ({_PART})")
add("bigram_dense", lambda s, d: part(s, d, True).select("p_partkey", F.array_size(F.array_remove(text.dense(F.col("pos")), 0)).alias("ones")), f"select p_partkey, len(pos)::int as ones from ({_PART})")
add("combined_name", lambda s, d: Registry.of(s, d).left.select("rec_id", score.combined_name().alias("name")), over_registry(f"select rec_id, case when coalesce(first_name, birth_name, last_name) is not null then concat({O.normal('first_name')}, {O.normal('birth_name')}, {O.normal('last_name')}) end as name from registry_left_"))
add("bigram_frequency", lambda s, d: part(s, d).select(F.explode("pos").alias("p")).groupBy("p").agg(F.count("*").alias("n")), f"select p, count(*) as n from (select unnest(pos) as p from ({_PART})) group by p")


def part_pairs(s, d):
    a, b = part(s, d).where("p_partkey % 50 = 0"), part(s, d).where("p_partkey % 50 = 1")
    return a.select([F.col(c).alias(f"a_{c}") for c in a.columns]).join(b.select([F.col(c).alias(f"b_{c}") for c in b.columns]), F.col("a_p_brand") == F.col("b_p_brand"))


_PAIRS = f"(select a.p_partkey as a_id, b.p_partkey as b_id, a.pos as a, b.pos as b, a.p_name as an, b.p_name as bn, a.p_size as az, b.p_size as bz from ({_PART}) a join ({_PART}) b on a.p_brand = b.p_brand where a.p_partkey % 50 = 0 and b.p_partkey % 50 = 1)"


def _ids():
    return F.col("a_p_partkey").alias("a_id"), F.col("b_p_partkey").alias("b_id")


for _name, _fraction, _num, _den in (
    ("dice", fields.dice_fraction, "2 * len(list_intersect(a, b))", "greatest(len(a) + len(b), 1)"),
    ("jaccard", fields.jaccard_fraction, "len(list_intersect(a, b))", "greatest(len(list_distinct(list_concat(a, b))), 1)"),
    ("overlap", fields.overlap_fraction, "len(list_intersect(a, b))", "greatest(least(len(a), len(b)), 1)"),
):
    add(f"{_name}_part_pairs", lambda s, d, f=_fraction: part_pairs(s, d).select(*_ids(), f(F.col("a_pos"), F.col("b_pos")).alias("f")).select("a_id", "b_id", "f.num", "f.den", F.round(F.col("f.num") / F.col("f.den"), 6).alias("value")), f"select a_id, b_id, ({_num})::bigint as num, ({_den})::bigint as den, round(({_num}) / ({_den}), 6) as value from {_PAIRS}")
add("levenshtein_part_pairs", lambda s, d: part_pairs(s, d).select(*_ids(), F.levenshtein("a_p_name", "b_p_name").alias("edits")), f"select a_id, b_id, levenshtein(an, bn)::int as edits from {_PAIRS}")
add("exact_similarity", lambda s, d: part_pairs(s, d).select(*_ids(), fields.equal_bit(F.col("a_p_size"), F.col("b_p_size")).alias("equal")), f"select a_id, b_id, (az = bz)::bigint as equal from {_PAIRS}")
add("completeness", lambda s, d: ex(s, d).select("rec_id", *[f"{f}_delta" for f in ("name", "city")]), O.query("select rec_id, nd as name_delta, cd as city_delta from ex"))
_RULES = {"min": "least(x.nd, y.nd)", "product": "x.nd * y.nd // 100", "left": "x.nd", "mean": "(x.nd + y.nd) // 2"}
add("pair_completeness_rules", lambda s, d: match.pairs(ex(s, d).where("rec_id < 10000010"), ey(s, d)).select("x_rec_id", "y_rec_id", *[score.pair_delta("name", r).cast("long").alias(f"by_{r}") for r in _RULES]), O.query(f"select x.rec_id as x_rec_id, y.rec_id as y_rec_id, {', '.join(f'({v})::bigint as by_{k}' for k, v in _RULES.items())} from ex x, ey y where x.rec_id < 10000010"))
add("explain_pairs", lambda s, d: match.explain(ex(s, d), ey(s, d), bp(s, d)).select("x_id", "y_id", "name_ppm", "city_ppm", "postcode_equal", "birth_day_equal"), O.query("select x_id, y_id, (2 * len(list_intersect(x.np, y.np)) * 1000000 // (greatest(len(x.np), 1) + greatest(len(y.np), 1)))::bigint as name_ppm, (2 * len(list_intersect(x.cp, y.cp)) * 1000000 // (greatest(len(x.cp), 1) + greatest(len(y.cp), 1)))::bigint as city_ppm, coalesce((x.postcode = y.postcode)::bigint, 0) as postcode_equal, coalesce((x.birth_day = y.birth_day)::bigint, 0) as birth_day_equal from bp join ex x on x.rec_id = x_id join ey y on y.rec_id = y_id", *_BASE))
add("link_one_by_size", lambda s, d: _link_one(s, d), O.query("select size, x_id, y_id, num, den from (select *, row_number() over (partition by size order by " + O.KEY + " desc, y_id) as rank from sc, (select unnest([1, 10, 25, 100]) as size) z where x_id = 10000000 and y_id < 20000000 + size) where rank = 1", O.SCORES))


def _link_one(s, d):
    one = ex(s, d).where("rec_id = 10000000")
    frames = [match.best_partners(one, ey(s, d).where(F.col("rec_id") < 20_000_000 + n)).select(F.lit(n).alias("size"), "x_id", "y_id", "num", "den") for n in (1, 10, 25, 100)]
    return frames[0].union(frames[1]).union(frames[2]).union(frames[3])


add("padded_link_all", lambda s, d: match.accept(match.best_partners(ex(s, d), match.pad(ey(s, d), 12_000, 90_000_000)), TAU), SQL["link_all"])
add("best_margin", lambda s, d: match.best_window(blocks.top(ex(s, d), ey(s, d), 2), 2).groupBy("x_id").agg((F.max(score.ppm(F.col("num"), F.col("den"))) - F.min(score.ppm(F.col("num"), F.col("den")))).alias("margin_ppm")), O.query("select x_id, max(num * 1000000 // den) - min(num * 1000000 // den) as margin_ppm from (" + O.best("sc", 2) + ") group by x_id", O.SCORES))
add("no_exact_copies", lambda s, d: Registry.of(s, d).side(0).join(Registry.of(s, d).side(1), list(ATTRIBUTES)).agg(F.count("*").alias("copies")), over_registry("select count(*) as copies from registry_left_ l join registry_right_ r on " + " and ".join(f"l.{a} = r.{a}" for a in ATTRIBUTES)))
add("overlap_rate", lambda s, d: truth(s, d).agg(F.count("*").alias("shared")).crossJoin(ex(s, d).agg(F.count("*").alias("records"))), over_registry("select (select count(*) from truth_) as shared, (select count(*) from registry_left_) as records"))
add("corruption_profile", lambda s, d: Registry.of(s, d).copy("l").groupBy("n_errors", "shuffled").agg(F.count("*").alias("n")), over_registry("select n_errors, shuffled, count(*) as n from copy_left group by all"))
add("key_links", lambda s, d: Registry.of(s, d).side(0).join(Registry.of(s, d).side(1).select(F.col("rec_id").alias("y_id"), "entity"), "entity").select(F.col("rec_id").alias("x_id"), "y_id"), over_registry("select * from truth_"))
# Cost.
_VALUES = lambda rows: ", ".join(str(r) for r in rows)
def databases(s, d):
    """(db, size): the customers of each day of orders are one database."""
    return cost.databases(table(s, d, "orders").select("o_custkey", "o_orderdate"))


DATABASES = "(select o_orderdate::date as db, count(distinct o_custkey) as size from orders where o_orderdate is not null group by 1 having count(distinct o_custkey) > 0)"
add("published_speedups", lambda s, d: cost.by_size(databases(s, d), cost.speedups).select("db", "size", "a", "b", "c", "mb"), f"select db, z.size, round(a2 / a3, 2)::double as a, round(b2 / b3, 2)::double as b, round(c2 / c3, 2)::double as c, round(m2 / m3, 2)::double as mb from {DATABASES} z asof join (select col0 as size, col1::double as a2, col2::double as a3, col3::double as b2, col4::double as b3, col5::double as c2, col6::double as c3, col7::double as m2, col8::double as m3 from (values {_VALUES(cost.PUBLISHED)})) k on z.size >= k.size")


def error_totals(s, d):
    """Error totals by threshold of the names' Dice, by filters (two) and by maps (three), over the pairs of one birth date; beside them the published totals."""
    none = F.array().cast("array<int>")
    date = ["birth_year", "birth_month", "birth_day"]
    of = lambda v, p: v.select(F.col("rec_id").alias(f"{p}_id"), *date, F.coalesce("name_pos", none).alias(f"{p}m")).withColumn(f"{p}f", bloom.filter_positions(F.col(f"{p}m")))
    pairs = of(ex(s, d), "x").join(of(ey(s, d), "y"), date)
    value = lambda a, b: F.call_function("div", 2 * fields.shared(F.col(a), F.col(b)) * 10_000, F.greatest(F.size(a) + F.size(b), F.lit(1)).cast("long"))
    judged = pairs.join(truth(s, d).withColumn("_t", F.lit(True)), ["x_id", "y_id"], "left").select(F.coalesce("_t", F.lit(False)).alias("good"), value("xf", "yf").alias("two"), value("xm", "ym").alias("three"))
    known = cost.error_totals(s).select("tau_bp", F.col("total_two").alias("published_two"), F.col("total_three").alias("published_three"))
    return cost.measured_totals(judged, truth(s, d)).join(F.broadcast(known), "tau_bp").select("tau_bp", "total_two", "total_three", "published_two", "published_three")


_BY_DATE = "select t.x_id is not null as good, 2 * len(list_intersect(f.np, g.np)) * 10000 // greatest(len(f.np) + len(g.np), 1) as two, 2 * len(list_intersect(x.np, y.np)) * 10000 // greatest(len(x.np) + len(y.np), 1) as three from ex x join ey y using (birth_year, birth_month, birth_day) join bx f on f.rec_id = x.rec_id join by_ g on g.rec_id = y.rec_id left join truth_ t on t.x_id = x.rec_id and t.y_id = y.rec_id"
_TOTAL = lambda v: f"(coalesce(sum((not good and {v} > tau_bp)::int - (good and {v} > tau_bp)::int), 0) + (select count(*) from truth_))::bigint as total_{v}"
add("published_error_totals", error_totals, O.query(f"select tau_bp, {_TOTAL('two')}, {_TOTAL('three')}, any_value(col1 + col2) as published_two, any_value(col3 + col4) as published_three from (select col0 as tau_bp, * from (values {_VALUES(cost.ERRORS)})) left join cd on true group by tau_bp", *_BLOOM[:2], ("cd", _BY_DATE)))
add("storage_per_record", lambda s, d: cost.storage(ex(s, d)), over_registry("select n as records, n * 226 as packed_bytes, n * 14400 as share_bytes, n * 126 as filter_bytes from (select count(*) as n from registry_left_)"))
# Relational operators on linkage results and native tables.
add("ops_join_theta_year", lambda s, d: Registry.of(s, d).left.alias("l").join(Registry.of(s, d).right.alias("r"), F.expr("l.last_name = r.last_name and abs(l.birth_year - r.birth_year) <= 2")).select(F.col("l.rec_id").alias("x_id"), F.col("r.rec_id").alias("y_id")), over_registry("select l.rec_id as x_id, r.rec_id as y_id from registry_left_ l join registry_right_ r on l.last_name = r.last_name and abs(l.birth_year - r.birth_year) <= 2"))
add("ops_join_semi_matched", lambda s, d: Registry.of(s, d).left.join(match.accept(bp(s, d), TAU).where("accepted"), F.col("rec_id") == F.col("x_id"), "left_semi").select("rec_id"), O.query(f"select x_id as rec_id from bp where num * 10000 > den * {TAU}", *_BASE))
add("ops_join_anti_unmatched", lambda s, d: Registry.of(s, d).left.join(match.accept(bp(s, d), TAU).where("accepted"), F.col("rec_id") == F.col("x_id"), "left_anti").select("rec_id"), O.query(f"select rec_id from ex where rec_id not in (select x_id from bp where num * 10000 > den * {TAU})", *_BASE))
add("ops_rollup_nations", lambda s, d: table(s, d, "customer").rollup("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n")), "select c_nationkey, c_mktsegment, count(*) as n from customer group by rollup (c_nationkey, c_mktsegment)")
add("ops_cube_patterns", lambda s, d: ex(s, d).cube("name_delta", "city_delta").agg(F.count("*").alias("n")), O.query("select nd as name_delta, cd as city_delta, count(*) as n from ex group by cube (nd, cd)"))
add("ops_ntile_scores", lambda s, d: bp(s, d).select("x_id", F.floor(F.col("score_ppm") / 50_000).alias("band")).groupBy("band").agg(F.count("*").alias("n")), O.query("select score_ppm // 50000 as band, count(*) as n from bp group by 1", *_BASE))
add("ops_json_props", lambda s, d: table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")), "select event_id, (props::json->>'k')::bigint as k from events")
add("ops_dates_split", lambda s, d: table(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofmonth("o_orderdate").alias("dd")), "select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, day(o_orderdate)::int as dd from orders")
add("ops_except_links", lambda s, d: baselines.deterministic(Registry.of(s, d).left, Registry.of(s, d).right, ("last_name", "birth_year")).exceptAll(truth(s, d)), over_registry("select l.rec_id as x_id, r.rec_id as y_id from registry_left_ l join registry_right_ r on l.last_name = r.last_name and l.birth_year = r.birth_year except all select x_id, y_id from truth_"))
add("ops_intersect_links", lambda s, d: baselines.deterministic(Registry.of(s, d).left, Registry.of(s, d).right, ("last_name", "birth_year")).intersect(truth(s, d)), over_registry("select l.rec_id as x_id, r.rec_id as y_id from registry_left_ l join registry_right_ r on l.last_name = r.last_name and l.birth_year = r.birth_year intersect select x_id, y_id from truth_"))
add("turn_links", lambda s, d: table(s, d, "conversations").where("text is not null").groupBy(F.md5("text").alias("digest")).agg(F.count_distinct("conv_id").alias("conversations")).where("conversations > 1"), "select md5(text) as digest, count(distinct conv_id) as conversations from conversations where text is not null group by 1 having count(distinct conv_id) > 1")
add("stream_arrivals", lambda s, d: arrivals.written(arrivals.first_arrivals(arrivals.events(s, d)).select("event_id", "user_id")), "select event_id, user_id from events")
add("stream_links_by_window", lambda s, d: arrivals.collected(arrivals.by_window(arrivals.events(s, d)).select(F.col("start").cast("string").alias("start"), "event_type", "n"), "complete"), "select strftime(time_bucket(interval 1 day, ts), '%Y-%m-%d %H:%M:%S') as start, event_type, count(*) as n from events group by 1, 2")

# The queries above that SQL keeps small, over whole tables and whole texts: no SQL, tests hold them against brute force.
add("pair_scores_all", lambda s, d: match.scored(match.pairs(ex(s, d), ey(s, d))))
add("pair_completeness_rules_all", lambda s, d: match.pairs(ex(s, d), ey(s, d)).select("x_rec_id", "y_rec_id", *[score.pair_delta("name", r).cast("long").alias(f"by_{r}") for r in _RULES]))
add("normalise_accents_all", lambda s, d: table(s, d, "documents").select("doc_id", F.md5(text.normalise(F.col("text"))).alias("digest")))


def all_part_pairs(s, d, maps=False):
    """Every two parts, the one of smaller key first; one side is sent where it is small, the other dealt over all cores."""
    a = part(s, d)
    if maps:
        packed = a.withColumn("_w", text.pack(F.coalesce("pos", F.array().cast("array<int>"))))
        a = packed.select(*a.columns, F.size("pos").alias("card"), *[F.col("_w")[i].alias(f"w{i}") for i in range(text.WORDS)])
    dealt = a.repartition(4 * s.sparkContext.defaultParallelism)
    if a.count() <= match.BROADCAST_ROWS:
        other = F.broadcast(a.select([F.col(c).alias(f"b_{c}") for c in a.columns]))
        return dealt.select([F.col(c).alias(f"a_{c}") for c in a.columns]).join(other, F.col("a_p_partkey") < F.col("b_p_partkey"))
    return dealt.select([F.col(c).alias(f"a_{c}") for c in a.columns]).join(a.select([F.col(c).alias(f"b_{c}") for c in a.columns]), F.col("a_p_partkey") < F.col("b_p_partkey"))


def all_part_dice(s, d):
    """Dice of every two parts from packed maps; the fraction of the lists, a missing name shares nothing that is known."""
    shared = fields.packed_shared([F.col(f"a_w{i}") for i in range(text.WORDS)], [F.col(f"b_w{i}") for i in range(text.WORDS)])
    num = F.when(F.col("a_pos").isNotNull() & F.col("b_pos").isNotNull(), 2 * shared)
    den = F.greatest(F.col("a_card") + F.col("b_card"), F.lit(1)).cast("long")
    rows = all_part_pairs(s, d, True).select(*_ids(), num.alias("num"), den.alias("den"))
    return rows.select("*", F.round(F.col("num") / F.col("den"), 6).alias("value"))


add("dice_part_pairs_all", all_part_dice)
for _name, _fraction in (("jaccard", fields.jaccard_fraction), ("overlap", fields.overlap_fraction)):
    add(f"{_name}_part_pairs_all", lambda s, d, f=_fraction: all_part_pairs(s, d).select(*_ids(), f(F.col("a_pos"), F.col("b_pos")).alias("f")).select("a_id", "b_id", "f.num", "f.den", F.round(F.col("f.num") / F.col("f.den"), 6).alias("value")))
add("levenshtein_part_pairs_all", lambda s, d: all_part_pairs(s, d).select(*_ids(), F.levenshtein("a_p_name", "b_p_name").alias("edits")))
add("exact_similarity_all", lambda s, d: all_part_pairs(s, d).select(*_ids(), fields.equal_bit(F.col("a_p_size"), F.col("b_p_size")).alias("equal")))

import veilmatch.plans.more  # noqa: E402, F401  registers the rest
