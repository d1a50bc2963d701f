"""Person registries derived from the given tables.

Every choice is a function of ``h(salt, key)``, the first 8 hexadecimal digits of an MD5, so one text
of SQL describes the registry in two dialects and gives the same rows in both. Ranks over all rows come from counts
of hash ranges and ranks within a range, never from one sorted partition.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from veilmatch.sources.tables import stored, table

ATTRIBUTES = ("first_name", "last_name", "birth_name", "city", "postcode", "birth_year", "birth_month", "birth_day")
STRINGS = ATTRIBUTES[:4]
KEYS_FROM, KEYS_TO = "qwertzuiopasdfghjklyxcvbnm", "wertzuiopqsdfghjklaxcvbnmy"
KINDS = ("substitute", "insert", "delete", "transpose", "blank", "keyboard", "phonetic", "misspell")
SPARK, DUCK = "spark", "duck"


def h(dialect: str, salt: str, key: str) -> str:
    text = f"concat('{salt}|', {key})"
    return f"cast(conv(substr(md5({text}), 1, 8), 16, 10) as bigint)" if dialect == SPARK else f"cast(concat('0x', substr(md5({text}), 1, 8)) as bigint)"


def div(dialect: str, a: str, b: str) -> str:
    return f"(({a}) div ({b}))" if dialect == SPARK else f"(({a}) // ({b}))"


def words_sql(dialect: str, documents: str) -> str:
    """(lang, word, n): runs of 4 to 10 ASCII letters."""
    if dialect == SPARK:
        rows = f"select lang, explode(regexp_extract_all(lower(text), '[a-z]+', 0)) as word from {documents}"
    else:
        rows = f"select lang, unnest(regexp_extract_all(lower(text), '[a-z]+')) as word from {documents}"
    return f"select lang, word, count(*) as n from ({rows}) w where length(word) between 4 and 10 group by lang, word"


def pool_sql(words: str, lang: str, most: int) -> str:
    return f"select word, row_number() over (order by n desc, word) - 1 as r from (select word, n from {words} where lang = '{lang}' order by n desc, word limit {most}) p"


def ranked_sql(rows: str, hashed: str, key: str, name: str) -> str:
    """Adds the rank of each row in the order of (hashed, key), from 0. One window over 4,096 counts, and one in each hash range."""
    return f"""
select t.*, o.before_ + row_number() over (partition by t.range_ order by t.{hashed}, t.{key}) - 1 as {name}
from (select *, {{div}} as range_ from {rows}) t
join (select range_, sum(n) over (order by range_) - n as before_ from (select {{div}} as range_, count(*) as n from {rows} group by 1) c) o on t.range_ = o.range_"""


def ranked(dialect: str, rows: str, hashed: str, key: str, name: str) -> str:
    return ranked_sql(rows, hashed, key, name).replace("{div}", div(dialect, hashed, "1048576"))


def original_sql(d: str, customer: str, pools: tuple[str, str, str]) -> str:
    """One person a customer key."""

    def skewed(salt: str, pool: str) -> str:
        v = f"({h(d, salt, 'c_custkey')} % 65536)"
        return div(d, f"{v} * {v} * (select count(*) from {pool})", "4294967296")

    given, family, cities = pools
    place = f"(8 * c_nationkey + {h(d, 'place', 'c_custkey')} % 8)"
    # A day of the year, all equally likely, becomes month and day by the lengths of the months in that year.
    years = div(d, f"80 * ({h(d, 'year1', 'c_custkey')} % 65536 + {h(d, 'year2', 'c_custkey')} % 65536)", "131072")
    return f"""
select k.entity, g.word as first_name, f.word as last_name, b.word as birth_name, c.word as city,
  cast(10000 + 11 * k.place as int) as postcode, k.birth_year, k.birth_month, k.birth_day
from (select c_custkey as entity, {skewed('given', given)} as rg, {skewed('family', family)} as rf, {skewed('birth', family)} as rb, {place} as place,
  cast(1930 + {years} as int) as birth_year, cast(1 + {h(d, 'month', 'c_custkey')} % 12 as int) as birth_month, cast(1 + {h(d, 'day', 'c_custkey')} % 28 as int) as birth_day
  from {customer}) k
left join {given} g on g.r = k.rg left join {family} f on f.r = k.rf left join {family} b on b.r = k.rb
left join {cities} c on c.r = k.place % (select greatest(count(*), 1) from {cities})"""


def corrupted_sql(d: str, rows: str, copy: str) -> str:
    """One dirty copy of every original, with what happened to it (n_errors, kinds, shuffled)."""
    hits = {a: f"({h(d, f'hit|{copy}|{a}', 'entity')} % 1000 < 100)" for a in ATTRIBUTES}
    flags = ", ".join(f"case when {c} then 1 else 0 end as hit_{a}" for a, c in hits.items())
    acts, before = [], "0"
    for a in ATTRIBUTES:
        acts.append(f"case when hit_{a} = 1 and {before} < 2 then 1 else 0 end as act_{a}")
        before += f" + hit_{a}"
    kinds = ", ".join(f"{h(d, f'kind|{copy}|{a}', 'entity')} % {8 if a in STRINGS else 2} as kind_{a}" for a in ATTRIBUTES)

    def dirty(a: str) -> str:
        if a not in STRINGS:
            shift = {"postcode": "postcode + 11", "birth_year": "birth_year + 1", "birth_month": "birth_month % 12 + 1", "birth_day": "birth_day % 28 + 1"}[a]
            return f"cast(case when act_{a} = 0 then {a} when kind_{a} = 0 then null else {shift} end as int)"
        p = f"cast(1 + {h(d, f'pos|{copy}|{a}', 'entity')} % greatest(length({a}), 1) as int)"
        letter = f"substr('abcdefghijklmnopqrstuvwxyz', cast(1 + {h(d, f'chr|{copy}|{a}', 'entity')} % 26 as int), 1)"
        head, at, tail = f"substr({a}, 1, {p} - 1)", f"substr({a}, {p}, 1)", f"substr({a}, {p} + 1)"
        phonetic = f"replace(replace(replace(replace(replace({a}, 'ph', 'f'), 'ck', 'k'), 'sch', 'sh'), 'z', 's'), 'v', 'f')"
        forms = [
            f"concat({head}, {letter}, {tail})", f"concat({head}, {letter}, {at}, {tail})", f"concat({head}, {tail})", f"concat({head}, substr({a}, {p} + 1, 1), {at}, substr({a}, {p} + 2))",
            "null", f"concat({head}, translate({at}, '{KEYS_FROM}', '{KEYS_TO}'), {tail})", phonetic, f"concat({head}, {at}, {at}, {tail})",
        ]
        return f"case when act_{a} = 0 or {a} is null then {a} " + " ".join(f"when kind_{a} = {k} then {f}" for k, f in enumerate(forms)) + " end"

    # Of rows whose date can be turned (both parts at most 12) the names and the date are shuffled in equal shares; of others the names.
    shuffle = h(d, f"shuffle|{copy}", "entity")
    blank = f"{h(d, f'nobirth|{copy}', 'entity')} % 1000 < 600"
    return f"""
select entity, case when names = 1 then last_name else first_name end as first_name, case when names = 1 then first_name else last_name end as last_name, birth_name, city, postcode, birth_year,
  case when dates = 1 then birth_day else birth_month end as birth_month, case when dates = 1 then birth_month else birth_day end as birth_day, n_errors, kinds, names + dates as shuffled
from (select entity, {', '.join(f'{dirty(a)} as {a}' for a in ATTRIBUTES)}, {' + '.join(f'act_{a}' for a in ATTRIBUTES)} as n_errors,
    concat({", ".join(f"case when act_{a} = 1 then concat('{a}:', cast(kind_{a} as varchar(9)), ' ') else '' end" for a in ATTRIBUTES)}) as kinds,
    case when shuf < 50 or (shuf < 100 and coalesce(birth_day, 31) > 12) then 1 else 0 end as names, case when shuf between 50 and 99 and birth_day <= 12 then 1 else 0 end as dates
  from (select *, {', '.join(acts)}
    from (select entity, first_name, last_name, case when {blank} then null else birth_name end as birth_name, city, postcode, birth_year, birth_month, birth_day,
      {flags}, {kinds}, {shuffle} % 1000 as shuf from {rows}) z) y) x"""


def pairs_sql(d: str, originals: str, left: str, right: str) -> str:
    """(entity, side, place, fields): which copy of which entity is on which side. Pairs equal in every field get one forced edit on the right."""
    n = div(d, "(select count(*) from {o}) * 2", "3").replace("{o}", originals)
    shared, only = div(d, f"{n} * 6", "10"), div(d, f"{n} * 4", "10")
    split = ranked(d, f"(select entity, {h(d, 'split', 'entity')} as hs from {originals})", "hs", "entity", "place")
    same = " and ".join(f"l.{a} is not distinct from r.{a}" for a in ATTRIBUTES)
    tail = "substr(r.last_name, 2)"  # of a missing name: DuckDB's concat takes it as empty, Spark's would give null
    edit = f"case when {same} then concat(case when substr(r.last_name, 1, 1) = 'x' then 'y' else 'x' end, {f"coalesce({tail}, '')" if d == SPARK else tail}) else r.last_name end"
    rest = ", ".join(f"r.{a}" for a in ATTRIBUTES if a != "last_name")
    return f"""
select l.entity, 0 as side, s.place, {', '.join(f'l.{a}' for a in ATTRIBUTES)} from {left} l join ({split}) s on l.entity = s.entity where s.place < {shared} + {only}
union all
select r.entity, 1 as side, s.place, r.first_name, {edit} as last_name, {rest.replace('r.first_name, ', '')}
from {right} r join {left} l on l.entity = r.entity join ({split}) s on r.entity = s.entity
where s.place < {shared} or (s.place >= {shared} + {only} and s.place < {shared} + 2 * {only})"""


def side_sql(d: str, placed: str, side: int) -> str:
    start = (10_000_000, 20_000_000)[side]
    rows = f"(select *, {h(d, f'id{side}', 'entity')} as hi from {placed} where side = {side})"
    return f"""
select cast({start} + rank_ as bigint) as rec_id, {"'left'" if side == 0 else "'right'"} as owner, {', '.join(ATTRIBUTES)}, entity from ({ranked(d, rows, 'hi', 'entity', 'rank_')}) q"""


def duck_views() -> str:
    """The registry as a chain of CTEs for DuckDB, without the word ``with``."""
    parts = [
        ("word_counts", words_sql(DUCK, "documents")),
        *((name, pool_sql("word_counts", lang, n)) for name, lang, n in (("pool_given", "en", 300), ("pool_family", "de", 600), ("pool_city", "es", 200))),
        ("person", original_sql(DUCK, "customer", ("pool_given", "pool_family", "pool_city"))),
        ("copy_left", corrupted_sql(DUCK, "person", "l")),
        ("copy_right", corrupted_sql(DUCK, "person", "r")),
        ("placed", pairs_sql(DUCK, "person", "copy_left", "copy_right")),
        ("registry_left_", side_sql(DUCK, "placed", 0)),
        ("registry_right_", side_sql(DUCK, "placed", 1)),
        ("truth_", "select l.rec_id as x_id, r.rec_id as y_id from registry_left_ l join registry_right_ r on l.entity = r.entity"),
    ]
    return ", ".join(f"{name} as materialized ({sql})" for name, sql in parts)


class Registry:
    """The derived frames over one folder of tables; each is built and written when it is asked for."""

    _held: dict[tuple[str, str], Registry] = {}

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder
        self._frames: dict[str, DataFrame] = {}

    @classmethod
    def of(cls, spark: SparkSession, folder: str) -> Registry:
        key = (spark.sparkContext.applicationId, folder)
        if key not in cls._held:
            cls._held.clear()
            cls._held[key] = cls(spark, folder)
        return cls._held[key]

    def _sql(self, name: str, text: str, **frames: DataFrame) -> DataFrame:
        if name not in self._frames:
            self._frames[name] = stored(self.spark.sql(text, **frames))
        return self._frames[name]

    @property
    def words(self) -> DataFrame:
        return self._sql("words", words_sql(SPARK, "{documents}"), documents=table(self.spark, self.folder, "documents").select("lang", "text"))

    def pool(self, lang: str, most: int) -> DataFrame:
        return self._sql(f"pool_{lang}", pool_sql("{words}", lang, most), words=self.words)

    @property
    def person(self) -> DataFrame:
        pools = {"given": self.pool("en", 300), "family": self.pool("de", 600), "city": self.pool("es", 200)}
        return self._sql("person", original_sql(SPARK, "{customer}", ("{given}", "{family}", "{city}")), customer=table(self.spark, self.folder, "customer").select("c_custkey", "c_nationkey"), **pools)

    def copy(self, side: str) -> DataFrame:
        return self._sql(f"copy_{side}", corrupted_sql(SPARK, "{person}", side), person=self.person)

    @property
    def placed(self) -> DataFrame:
        return self._sql("placed", pairs_sql(SPARK, "{person}", "{l}", "{r}"), person=self.person, l=self.copy("l"), r=self.copy("r"))

    def side(self, side: int) -> DataFrame:
        return self._sql(f"side_{side}", side_sql(SPARK, "{placed}", side), placed=self.placed)

    @property
    def left(self) -> DataFrame:
        return self.side(0).drop("entity")

    @property
    def right(self) -> DataFrame:
        return self.side(1).drop("entity")

    @property
    def truth(self) -> DataFrame:
        return self._sql("truth", "select l.rec_id as x_id, r.rec_id as y_id from {l} l join {r} r on l.entity = r.entity", l=self.side(0), r=self.side(1))
