"""Place fixtures as SQL that both engines evaluate: pure functions of ``part`` (see FIXTURES.md).

``ctes(dialect)`` gives the common table expressions in order; Spark reads ``part`` from a path, the oracle from
its view.  Every random-looking choice is an integer hash of a key.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

#: Role, reliability rank, shares per mille of entities, addresses, names and tags.
ROLES = [
    ("authority_map", 1, 140, 693, 1000, 894),
    ("authority_registry", 2, 55, 1000, 1000, 1000),
    ("social_places", 3, 900, 948, 999, 0),
    ("commercial_map", 4, 251, 989, 1000, 233),
    ("open_map", 5, 44, 756, 327, 0),
]
#: Tasks that make the places.
DEAL = 32
SOUTH, WEST = 1.310157, 103.923457
M_PER_LAT, M_PER_LON = 111194.93, 111165.0


def h(x: str, dialect: str) -> str:
    """First 8 hex digits of an md5 as a number."""
    if dialect == "spark":
        return f"cast(conv(substr(md5({x}), 1, 8), 16, 10) as bigint)"
    return f"(('0x' || substr(md5({x}), 1, 8))::BIGINT)"


def d(x: float) -> str:
    return f"cast({x} as double)"


def ctes(dialect: str, part: str = "part") -> list[tuple[str, str]]:
    def hk(tag: str, key: str = "k") -> str:
        return h(f"'{tag}' || {key}", dialect)

    def e(tag: str) -> str:
        return hk(tag, "cast(e as string)" if dialect == "spark" else "cast(e as varchar)")

    div = "div" if dialect == "spark" else "//"
    string = "string" if dialect == "spark" else "varchar"
    array = "array({})" if dialect == "spark" else "[{}]"
    # the table is small and its places are many: without a deal one task would make them all
    deal = f"/*+ REPARTITION({DEAL}, p_partkey) */ " if dialect == "spark" else ""
    empty = "cast(array() as array<string>)" if dialect == "spark" else "cast([] as varchar[])"
    box = "named_struct('south', {}, 'west', {}, 'north', {}, 'east', {})" if dialect == "spark" else "struct_pack(south := {}, west := {}, north := {}, east := {})"
    roles = " union all ".join(f"select '{r}' as src, {k} as rank, {s} as share, {a} as has_addr, {n} as has_name, {t} as has_tags" for r, k, s, a, n, t in ROLES)
    word = f"element_at(split(p_name, ' '), {{}})" if dialect == "spark" else "split_part(p_name, ' ', {})"
    noun, adjective = (word.format(2), word.format(1))
    segment = {0: "BUILDING", 1: "MACHINERY"}
    out = [
        ("roles", roles),
        ("ent0", f"select {deal}cast(p_partkey as bigint) as e, p_name, p_brand, p_type, p_size, (select count(*) from {part}) as n from {part}"),
        ("ent1", f"select *, {d(49.0)} * sqrt(cast(n as double)) as side_m, {e('c')} % 2 = 0 as clustered, case when {e('c')} % 2 = 0 then 'k' || cast({e('k')} % greatest(1, n {div} 40) as {string}) else 'e' || cast(e as {string}) end as anchor from ent0"),
        ("entity", f"select *, ({hk('x', 'anchor')} % 100000) / {d(100000.0)} * side_m + case when clustered then ({e('u')} % 1200) / {d(10.0)} - {d(60.0)} else {d(0.0)} end as x, ({hk('y', 'anchor')} % 100000) / {d(100000.0)} * side_m + case when clustered then ({e('v')} % 1200) / {d(10.0)} - {d(60.0)} else {d(0.0)} end as y from ent1"),
        ("pr0", f"select ent.*, r.src, r.rank, r.share, r.has_addr, r.has_name, r.has_tags, cast(ent.e as {string}) || ':' || r.src as k from entity ent cross join roles r"),
        ("pr1", f"select *, case when {hk('j')} % 50 = 0 then {d(2.0)} else {d(1.0)} end as far from pr0 where {hk('p', f"cast(e as {string}) || src")} % 1000 < share"),
        ("pr2", f"""select *, {d(SOUTH)} + (y + far * (({hk('jy')} % 800) / {d(10.0)} - {d(40.0)})) / {d(M_PER_LAT)} as lat,
            {d(WEST)} + (x + far * (({hk('jx')} % 800) / {d(10.0)} - {d(40.0)})) / {d(M_PER_LON)} as lon,
            {hk('nv')} % 5 as nv, {hk('t')} % 6 as tv, p_name || ' ' || p_brand as plain,
            cast(1 + {e('b')} % 900 as {string}) as block,
            'Nation ' || cast((cast(floor(x / {d(200.0)}) as bigint) * 7 + cast(floor(y / {d(200.0)}) as bigint) * 3 + 2500) % 25 as {string}) as road from pr1"""),
        ("poi_raw", f"""select k as uid, e, src, cast(rank as int) as rank, lat, lon,
            case when {hk('n')} % 1000 >= has_name then null when nv = 0 then plain when nv = 1 then p_brand || ' ' || p_name when nv = 2 then upper(plain)
                 when nv = 3 then plain || ' ' || p_type else substr(plain, 1, 2) || substr(plain, 4) end as name,
            case when {hk('a')} % 1000 >= has_addr then null else block || ' ' || case {hk('av')} % 3 when 0 then road when 1 then upper(road) else lower(road) end
                 || case when {hk('st')} % 2 = 0 then ' Street' else ' St' end || ', ASIA' end as address,
            case when src = 'social_places' or tv = 0 then {array.format('p_type')} when tv = 1 then {array.format('lower(p_type)')} when tv = 2 then {array.format(noun + " || ' ' || p_type")}
                 when tv = 3 then {array.format("lower(p_type) || 's'")} when tv = 4 then {array.format(f"case when e % 2 = 0 then '{segment[0]}' else '{segment[1]}' end")}
                 else {array.format(adjective + f" || ' {segment[0]}'")} end as place_type,
            case when {hk('g')} % 1000 < has_tags then {array.format(f"p_brand, 'size:' || cast(p_size as {string})")} else {empty} end as tags,
            case when src in ('authority_map', 'social_places', 'commercial_map') then {box.format(f"lat - (5 + p_size / {d(2.0)}) / {d(M_PER_LAT)}", f"lon - (5 + p_size / {d(2.0)}) / {d(M_PER_LON)}", f"lat + (5 + p_size / {d(2.0)}) / {d(M_PER_LAT)}", f"lon + (5 + p_size / {d(2.0)}) / {d(M_PER_LON)}")} end as bounds,
            date_add(date '2021-07-01', {"cast(" + hk('d') + " % 62 as int)" if dialect == "spark" else "to_days(cast(" + hk('d') + " % 62 as int))"}) as extraction_date,
            false as requires_verification, side_m, x, y, {hk('r')} % 20 = 0 as repeats from pr2"""),
    ]
    if dialect != "spark":
        out[-1] = ("poi_raw", out[-1][1].replace("date_add(date '2021-07-01', ", "cast(date_add(date '2021-07-01', ").replace(" as extraction_date", " as date) as extraction_date"))
    return out


def _with(parts: list[tuple[str, str]]) -> str:
    return "WITH " + ",\n".join(f"{n} AS ({q})" for n, q in parts)


def duck(*more: tuple[str, str], final: str) -> str:
    """An oracle query with the fixture's expressions before it."""
    return _with([*ctes("duck"), *more]) + "\n" + final


def poi_raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.sql(_with(ctes("spark", f"parquet.`{sf_dir}/part.parquet`")) + " SELECT * FROM poi_raw")


def poi_raw_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """With the repeats that overlapping boxes return."""
    p = poi_raw(spark, sf_dir)
    return p.unionByName(p.where("repeats"))


def entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.sql(_with(ctes("spark", f"parquet.`{sf_dir}/part.parquet`")) + " SELECT * FROM entity")
