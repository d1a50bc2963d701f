"""DuckDB SQL of the linkage, written on lists of bigrams and set operations.

The engine packs maps into words; these texts do not, so an error of the encoding shows.
"""

from __future__ import annotations

from veilmatch.functions.text import ALPHABET, FOLD_FROM, FOLD_TO
from veilmatch.operators.registry import duck_views
from veilmatch.operators.score import CODES, WEIGHTS


def normal(c: str) -> str:
    return f"trim(regexp_replace(replace(translate(lower({c}), '{FOLD_FROM}', '{FOLD_TO}'), 'ß', 'ss'), '[^a-z. *-]', '*', 'g'))"


def positions(c: str, q: int = 2) -> str:
    place = " ".join(f"{'+' if k else ''} {30 ** (q - 1 - k)} * (instr('{ALPHABET}', substr({c}, i + {k}, 1)) - 1)" for k in range(q))
    return f"case when {c} is null then null else list_sort(list_distinct(list_transform(range(1, length({c}) - {q - 2}), lambda i: ({place})::int))) end"


def long_positions(c: str, q: int = 2) -> str:
    """Of long texts, whose letters are split once."""
    rank = lambda k: f"(instr('{ALPHABET}', cs[i + {k}]) - 1)"
    place = " + ".join(f"{30 ** (q - 1 - k)} * {rank(k)}" for k in range(q))
    return f"list_sort(list_distinct(list_transform(range(1, len(cs) - {q - 2}), lambda i: ({place})::int)))".replace("cs", f"{c}")


def encoded(rows: str, mode: str = "components") -> str:
    name = f"case when coalesce(first_name, birth_name, last_name) is not null then concat({normal('first_name')}, {normal('birth_name')}, {normal('last_name')}) end"
    present = "(first_name is not null)::int + (birth_name is not null)::int + (last_name is not null)::int"
    nd = f"case {present} when 3 then 100 when 2 then 66 when 1 then 33 else 0 end" if mode == "components" else f"case when {present} > 0 then 100 else 0 end"
    return f"""select rec_id, {', '.join(CODES)}, coalesce({positions('nm')}, []::int[]) as np, coalesce({positions('ct')}, []::int[]) as cp, nd, (city is not null)::int * 100 as cd
    from (select *, {name} as nm, {normal('city')} as ct, {nd} as nd from {rows})"""


def scores(x: str, y: str, weights: dict[str, int] = WEIGHTS, rule: str = "least(x.nd, y.nd)", dice: tuple[str, str] | None = None, where: str = "true") -> str:
    """(x_id, y_id, num, den) of comparable pairs."""
    n, c = ((f"len(list_intersect(x.{p}, y.{p}))", f"greatest(len(x.{p}), 1) + greatest(len(y.{p}), 1)") for p in ("np", "cp"))
    agree = " + ".join(f"coalesce((x.{f} = y.{f})::int, 0) * {100 * weights[f]}" for f in CODES)
    have = " + ".join(f"(x.{f} is not null and y.{f} is not null)::int * {100 * weights[f]}" for f in CODES)
    return f"""select x_id, y_id, (dn * a * e + dc * c * b + agree * b * e)::bigint as num, ((dn + dc + have) * b * e)::bigint as den
    from (select x.rec_id as x_id, y.rec_id as y_id, ({rule})::bigint * {weights['name']} as dn, (x.cd * y.cd // 100)::bigint * {weights['city']} as dc, 2 * {n[0]} as a, {n[1]} as b, 2 * {c[0]} as c, {c[1]} as e,
      ({agree})::bigint as agree, ({have})::bigint as have from {x} x, {y} y where {where}) p where dn + dc + have > 0"""


KEY = "(((num << 31) // den) << 31 | ((((num << 31) % den) << 31) // den))"


def best(rows: str, k: int = 1) -> str:
    return f"select * from (select *, row_number() over (partition by x_id order by {KEY} desc, y_id) as rank from {rows}) where rank <= {k}"


def chain(*more: tuple[str, str], mode: str = "components") -> list[tuple[str, str]]:
    return [("ex", encoded("registry_left_", mode)), ("ey", encoded("registry_right_", mode)), *more]


def query(body: str, *more: tuple[str, str], mode: str = "components") -> str:
    parts = ", ".join(f"{n} as materialized ({s})" for n, s in chain(*more, mode=mode))
    return f"with {duck_views()}, {parts} {body}"


SCORES = ("sc", scores("ex", "ey"))
BEST = ("bp", f"select x_id, y_id, num, den, (num * 1000000) // den as score_ppm from ({best('sc')})")
JUDGED = ("jd", f"select b.x_id, num, den, {KEY} as k, score_ppm, coalesce(b.y_id = t.y_id, false) as is_true, t.y_id is not null as has_partner from bp b left join truth_ t on b.x_id = t.x_id")
SWEEP = """select tau_bp, sum((ok and not is_true)::int)::bigint as fp, sum((has_partner and not ok)::int)::bigint as fn, sum((ok and not is_true)::int + (has_partner and not ok)::int)::bigint as total,
 sum((ok and is_true)::int)::bigint as tp, sum((not ok and not has_partner)::int)::bigint as tn
from (select *, num * 10000 > den * tau_bp as ok from jd, (select unnest({taus})::int as tau_bp)) group by tau_bp"""
