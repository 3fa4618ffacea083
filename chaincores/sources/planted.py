"""Listings with known groups, made by arithmetic on the keys of ``customer``, ``part``, ``nation`` and ``orders``.

Every view has rid, name, phone, url, url2, state, category, gold. The same expressions are written for Spark and for
DuckDB; only the salted hash and integer division differ.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

COLUMNS = ("rid", "name", "phone", "url", "url2", "state", "category", "gold")


class Dialect:
    def __init__(self, spark: bool):
        self.spark = spark

    def h(self, key: str, salt: str) -> str:
        digits = f"substr(md5(concat(cast({key} as string), '|{salt}')), 1, 7)"
        return f"cast(conv({digits}, 16, 10) as bigint)" if self.spark else f"cast(concat('0x', {digits.replace('string', 'varchar')}) as bigint)"

    def text(self, prefix: str, key: str) -> str:
        return f"concat('{prefix}', cast({key} as {'string' if self.spark else 'varchar'}))"

    def name(self, prefix: str, key: str) -> str:
        return f"substr(md5({self.text(prefix, key)}), 1, 10)"


def _rows(view: str, d: Dialect, n: str) -> str:
    """rid, gold, name, phone, url, url2 of a view; n is the number of customers (or orders) as SQL."""
    h, t = d.h, d.text
    view, whole = view.removesuffix("_all"), view.endswith("_all")
    few, some = ("", "") if whole else (" where c_custkey % 5 = 0", " where c_custkey % 5 < 2")
    nine, fourteen = (45, 35) if whole else (9, 14)  # chains grow with the rows
    div = "div" if d.spark else "//"
    if view in ("p1", "n2"):
        base, key = ("customer", "c_custkey") if view == "p1" else ("orders", "o_orderkey")
        return f"""
        select rid, case when single then -rid - 1 else chain end as gold,
          concat(case when single and {h('rid', 'q')} % 100 >= 17 then {d.name('u', 'rid')} else {d.name('n', 'chain % names')} end, case when {h('rid', 'v')} % 100 < 8 then ' inc' else '' end) as name,
          case when {h('rid', 'p')} % 100 < 12 then null when single or {h('rid', 'p')} % 100 >= 67 then {t('local', 'rid')}
            when {h('rid', 'w')} % 100 < 2 then {t('main', '(chain + names) % chains')} else {t('main', 'chain')} end as phone,
          case when {h('rid', 'r')} % 100 < 25 then null when single or {h('rid', 'r')} % 100 >= 85 then {t('site', '1000000 + rid')} else {t('site', 'chain')} end as url,
          case when not single and {h('rid', 'x')} % 100 < 3 then {t('site', '(chain + names) % chains')} end as url2
        from (select {key} as rid, {h(key, 's')} % 100 < 24 as single, {h(key, 'c')} % chains as chain, chains, (4 * chains) {div} 5 as names
          from {base} cross join (select greatest(30, {n} {div} 69) as chains) g) b"""
    if view == "p2":
        return f"""
        select rid, 0 as gold, 'one chain' as name,
          case when q >= 2219 then null when {h('rid', 'p')} % 100 < 30 then 'main' when {h('rid', 'p')} % 100 < 90 then {t('local', 'rid')} end as phone,
          case when q < 1499 then 'ua' when q < 2223 then 'ub' end as url, case when q >= 1369 and q < 1499 then 'ub' end as url2
        from (select c_custkey as rid, {h('c_custkey', 'u')} % 2446 as q from customer) b"""
    if view == "p3":
        return f"""
        select rid, case when single then -rid - 1 else chain end as gold, 'same name' as name,
          case when {h('rid', 'p')} % 100 < 10 then null when single or {h('rid', 'p')} % 100 >= 60 then {t('local', 'rid')} else {t('main', 'chain')} end as phone,
          case when {h('rid', 'r')} % 100 < 20 then null when single then {t('site', '1000000 + rid')} else {t('site', 'chain')} end as url,
          case when not single and {h('rid', 'x')} % ({n} {div} 45) = 0 then {t('site', f'(chain + 1) % {nine}')} end as url2
        from (select c_custkey as rid, {h('c_custkey', 's')} % 1000 < 16 as single, {h('c_custkey', 'c')} % {nine} as chain from customer{few}) b"""
    if view in ("p4", "p4p"):
        fixed = view == "p4p"
        return f"""
        select rid, chain as gold, case when {'true' if fixed else 'false'} or bad then 'wrong name' else {d.name('n', 'chain')} end as name,
          case when {h('rid', 'p')} % 100 < 20 then null when {h('rid', 'p')} % 100 < 70 then {t('main', 'chain')} else {t('local', 'rid')} end as phone,
          case when bad and not ({'true' if fixed else 'false'}) and not kept then 'wrongsite' else {t('site', 'chain')} end as url,
          case when bad and kept and not ({'true' if fixed else 'false'}) then 'wrongsite' end as url2
        from (select c_custkey as rid, {h('c_custkey', 'c')} % {fourteen} as chain, {h('c_custkey', 'b')} % 1149 < 708 as bad,
          {h('c_custkey', 'c')} % {fourteen} = 0 or {h('c_custkey', 'y')} % ((2 * {n}) {div} 70) = 0 as kept from customer{some}) b"""
    if view == "p5":
        base = d.name("i", "inst")
        return f"""
        select rid, case when single then -rid - 1 else inst end as gold,
          concat(case when single then {d.name('u', 'rid')} else {base} end, case {h('rid', 'v')} % 10 when 0 then ' lab' when 1 then ' dept' else '' end) as name,
          case when {h('rid', 'p')} % 100 < 25 then null when single then {t('prefix', '1000000 + rid')} else {t('prefix', 'inst')} end as phone,
          case when {h('rid', 'r')} % 100 < 15 then null when single or {h('rid', 'r')} % 100 >= 90 then 'freemail' else {t('server', 'inst')} end as url,
          cast(null as {'string' if d.spark else 'varchar'}) as url2
        from (select c_custkey as rid, {h('c_custkey', 's')} % 100 < 27 as single, {h('c_custkey', 'c')} % greatest(1, {f'{n}' if whole else f'({n} * 2 {div} 5)'} * 71 {div} 590) as inst from customer{some}) b"""
    if view == "p5_raw":
        base = d.name("i", "inst")
        text = "string" if d.spark else "varchar"
        return f"""
        select rid, case when single then -rid - 1 else inst end as gold,
          concat(case when single then {d.name('u', 'rid')} else {base} end, case {h('rid', 'v')} % 10 when 0 then ' lab' when 1 then ' dept' else '' end) as name,
          case when {h('rid', 'p')} % 100 >= 25 then concat(cast(100 + (case when single then rid * 7 else inst end) % 900 as {text}), {t('-55', 'rid')}) end as phone,
          case when {h('rid', 'r')} % 100 >= 15 then concat({t('u', 'rid')}, '@', case when single or {h('rid', 'r')} % 100 >= 90 then 'freemail' else {t('server', 'inst')} end, '.org') end as url,
          case when {h('rid', 'a')} % 100 < 60 then concat({d.name('street', 'case when single then -rid else inst end')}, {t(' road ', 'rid % 7')}) end as url2
        from (select c_custkey as rid, {h('c_custkey', 's')} % 100 < 27 as single, {h('c_custkey', 'c')} % greatest(1, {n} * 71 {div} 590) as inst from customer) b"""
    raise ValueError(view)


#: The ``_all`` views have all customer rows, with chains in proportion; ``p5_raw`` has whole phone numbers, mail and street addresses.
VIEWS = ("p1", "p2", "p3", "p4", "p4p", "p5", "n2", "p3_all", "p4_all", "p4p_all", "p5_all", "p5_raw")
WHOLE = {"p1": "p1", "p2": "p2", "p3": "p3_all", "p4": "p4_all", "p4p": "p4p_all", "p5": "p5_all"}


def view_sql(view: str, spark: bool, n: str, parts: str) -> str:
    """The whole view: state and category are joined by keys."""
    d = Dialect(spark)
    h = d.h
    return f"""
    select r.rid, r.name, r.phone, r.url, r.url2, s.n_name as state, k.p_type as category, r.gold
    from (select *, case when gold >= 0 and {h('rid', 'st')} % 100 < 70 then gold % 25 else {h('rid', 'own')} % 25 end as state_key,
      case when {h('rid', 'kx')} % 100 < 10 then {h('rid', 'ko')} else {h('gold', 'k')} end % {parts} as part_key from ({_rows(view, d, n)}) v) r
    join nation s on s.n_nationkey = r.state_key join part k on k.p_partkey = r.part_key"""


#: Parts of the keys for each core.
SHARES = 2


def listings(spark: SparkSession, sf_dir: str, view: str = "p1") -> DataFrame:
    """A planted view as a DataFrame; the sizes in its arithmetic are table counts."""
    tables = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("customer", "orders", "nation", "part")}
    base, key = ("orders", "o_orderkey") if view == "n2" else ("customer", "c_custkey")
    n = tables[base].count()
    # a row's key is a few bytes and its hashes are long work, so keys of one small file are dealt to all cores
    tables[base] = tables[base].select(key).repartition(SHARES * spark.sparkContext.defaultParallelism)
    sql = view_sql(view, True, str(n), str(tables["part"].count()))
    for t in tables:
        sql = re.sub(rf"\b(from|join) {t}\b", rf"\1 {{{t}}}", sql)
    return spark.sql(sql, **tables)


def listings_sql(view: str) -> str:
    base = "orders" if view == "n2" else "customer"
    return view_sql(view, False, f"(select count(*) from {base})", "(select count(*) from part)")
