"""Replies and side inputs derived from the given tables, by formulae that Spark and DuckDB evaluate alike.

Every relation is one SELECT over earlier relations and given tables. ``relation`` gives it as a lazy DataFrame; ``sql`` gives the text for
either engine, which is how the oracle gets the same input.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from devicelens.sources.stored import stored_path

GIVEN = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
SCAN_1, SCAN_2, SCAN_SECONDS, V4_BASE, AS_SPAN = 1704672000, 1705190400, 345600, 335544320, 262144
#: The public special-purpose IPv4 blocks (first, last, why).
SPECIAL_V4 = (
    ("0.0.0.0", 8, "this network"), ("10.0.0.0", 8, "private"), ("100.64.0.0", 10, "shared"), ("127.0.0.0", 8, "loopback"), ("169.254.0.0", 16, "link local"),
    ("172.16.0.0", 12, "private"), ("192.0.0.0", 24, "protocol assignments"), ("192.0.2.0", 24, "documentation"), ("192.168.0.0", 16, "private"), ("198.18.0.0", 15, "benchmarking"),
    ("198.51.100.0", 24, "documentation"), ("203.0.113.0", 24, "documentation"), ("224.0.0.0", 4, "multicast"), ("240.0.0.0", 4, "reserved"),
)


def special_ranges() -> list[tuple[int, int, str]]:
    """(first, last, why) of the special blocks as numbers."""
    found = []
    for dotted, length, why in SPECIAL_V4:
        a, b, c, d = map(int, dotted.split("."))
        low = a << 24 | b << 16 | c << 8 | d
        found.append((low, low + (1 << (32 - length)) - 1, why))
    return found


class Dialect:
    """The few spellings in which the engines differ."""

    def __init__(self, spark: bool):
        self.spark = spark
        self.div = "div" if spark else "//"

    def number(self, hexadecimal: str) -> str:
        return f"cast(conv({hexadecimal}, 16, 10) as bigint)" if self.spark else f"('0x' || {hexadecimal})::bigint"

    def h(self, key: str, salt: str) -> str:
        return self.number(f"substr(md5(concat({key}, '|', '{salt}')), 1, 8)")

    def u(self, key: str, salt: str, m: int) -> str:
        return f"({self.h(key, salt)} % {m})"

    def md(self, key: str, salt: str, n: int) -> str:
        return f"substr(md5(concat({key}, '|', '{salt}')), 1, {n})"

    def dotted(self, x: str) -> str:
        d = self.div
        return f"concat({x} {d} 16777216, '.', ({x} {d} 65536) % 256, '.', ({x} {d} 256) % 256, '.', {x} % 256)"

    def seconds(self, ts: str) -> str:
        return f"cast(unix_seconds(cast({ts} as timestamp)) as bigint)" if self.spark else f"cast(floor(epoch({ts})) as bigint)"

    def days(self, ts: str) -> str:
        return f"cast(datediff({ts}, timestamp_ntz '1995-01-01') as bigint)" if self.spark else f"cast(datediff('day', timestamp '1995-01-01', {ts}) as bigint)"

    def brand_number(self, brand: str) -> str:
        return f"cast(regexp_extract({brand}, '[0-9]+', 0) as bigint)"


def _definitions(q: Dialect) -> dict[str, tuple[tuple[str, ...], str]]:
    """name -> (relations it reads, SELECT)."""
    u, md, d = q.u, q.md, q.div
    cube = lambda r: f"(1 + (25 * {r} * {r} * {r}) {d} 1000000000)"
    made: dict[str, tuple[tuple[str, ...], str]] = {}
    made["sizes"] = (("supplier", "customer"), "SELECT (SELECT count(*) FROM {supplier}) AS ns, (SELECT count(*) FROM {customer}) AS nc")
    made["device_draws"] = (
        ("customer", "sizes"),
        f"""SELECT c.c_custkey AS d, s.ns AS ns, s.nc AS nc, (s.ns * {u('c.c_custkey', 'as', 10000)} * {u('c.c_custkey', 'as', 10000)}) {d} 100000000 AS asn,
            {u('c.c_custkey', 'vmix', 100)} AS vmix, {u('c.c_custkey', 'vend', 1000)} AS own, {u('c.c_custkey', 'fmt', 100)} AS f, {u('c.c_custkey', 'up', 10000)} AS up
        FROM {{customer}} c CROSS JOIN {{sizes}} s""",
    )
    made["device_vendor"] = (
        ("device_draws",),
        f"SELECT *, CASE WHEN vmix < 80 THEN {cube(u('asn', 'vend', 1000))} ELSE {cube('own')} END AS vendor_no FROM {{device_draws}}",
    )
    mac = f"""CASE WHEN {u('d', 'clone', 100)} < 2 THEN concat(mac_prefix, '000001') WHEN {u('d', 'badoui', 1000)} < 8 THEN concat('f2', {md('d', 'x', 10)})
        ELSE concat(mac_prefix, {md('d', 'nic', 6)}) END"""
    v4 = f"CASE WHEN {u('d', 'priv', 100)} < 30 THEN concat('0a', {md('d', 'p', 6)}) ELSE printf('%08x', {V4_BASE} + asn * {AS_SPAN} + d) END"
    odd = f"CASE WHEN {u('d', 'nm', 100)} < 25 THEN {q.number(md('d', 'n1', 12))} ELSE {q.number(md('d', 'n1', 12))} & {q.number(md('d', 'n2', 12))} END"
    made["device"] = (
        ("device_vendor",),
        f"""SELECT d AS device, asn, vendor_no, enterprise, mac_prefix, f,
            CASE WHEN {u('d', 'short', 100)} < 5 THEN concat('80', {md('d', 'sh', 4)})
                WHEN {u('d', 'prom', 200)} = 0 THEN concat(printf('%08x', 2147483648 + enterprise), '05', '0011223344556677')
                WHEN f < 58 THEN concat(printf('%08x', 2147483648 + enterprise), '03', {mac})
                WHEN f < 62 THEN concat(printf('%08x', 2147483648 + enterprise), '01', {v4})
                WHEN f < 63 THEN concat(printf('%08x', 2147483648 + enterprise), '02', '20010db8', {md('d', 'v6', 24)})
                WHEN f < 65 THEN concat(printf('%08x', 2147483648 + enterprise), '04', lower(hex(concat('rtr-', d))))
                WHEN f < 77 THEN concat(printf('%08x', 2147483648 + enterprise), '05', {md('d', 'oct', 16)})
                WHEN f < 88 THEN concat(printf('%08x', 2147483648 + enterprise), '80', {md('d', 'agt', 16)})
                ELSE concat('03', printf('%012x', {odd})) END AS engine_id,
            CASE WHEN {u('d', 'zb', 100)} < 3 THEN 0 ELSE 1 + {u('d', 'boots', 200)} END AS boots,
            {SCAN_1} - 3600 - (1200 * 86400 * ((up * up) {d} 10000)) {d} 10000 AS boot_epoch,
            {u('d', 'rb', 100)} < 14 AS rebooted, {u('d', 'fam', 100)} AS fam, {u('d', 'fut', 1000)} < 2 AS future, ns, nc
        FROM (SELECT *, CASE WHEN f >= 77 AND f < 88 THEN 8999 ELSE 9000 + vendor_no END AS enterprise, substr(md5(concat('oui', '|', vendor_no)), 1, 6) AS mac_prefix FROM {{device_vendor}}) x""",
    )
    made["address"] = (
        ("orders", "device"),
        f"""SELECT a, d, asn, family, CASE WHEN family = 4 THEN {q.dotted('v4')} ELSE concat('2001:0db8:', printf('%04x', asn), '::', printf('%x', a)) END AS addr, v4
        FROM (SELECT o.o_orderkey AS a, o.o_custkey AS d, v.asn AS asn, {V4_BASE} + v.asn * {AS_SPAN} + o.o_orderkey % {AS_SPAN} AS v4,
            CASE WHEN v.fam < 88 OR (v.fam >= 93 AND {u('o.o_orderkey', 'fam', 100)} < 60) THEN 4 ELSE 6 END AS family
            FROM {{orders}} o JOIN {{device}} v ON v.device = o.o_custkey) x""",
    )
    jitter = f"""CASE WHEN {u('a', 'jc', 100)} < 70 THEN {u("concat(a, '|', scan)", 'jit', 5)} - 2 WHEN {u('a', 'jc', 100)} < 85 THEN {u("concat(a, '|', scan)", 'jit', 13)} - 6
        ELSE {u("concat(a, '|', scan)", 'jit', 241)} - 120 END"""
    made["replies_sent"] = (
        ("address", "sizes"),
        f"""SELECT x.*, CASE WHEN scan = 2 AND {u('a', 'churn', 100)} < 5 THEN (d + 1) % nc ELSE d END AS answering,
            CASE WHEN scan = 1 THEN {SCAN_1} ELSE {SCAN_2} END + {u("concat(a, '|', scan)", 'rx', SCAN_SECONDS)} AS recv_s
        FROM (SELECT p.*, s.scan AS scan, z.nc AS nc FROM {{address}} p CROSS JOIN (SELECT 1 AS scan UNION ALL SELECT 2 AS scan) s CROSS JOIN {{sizes}} z) x
        WHERE {u('a', 'resp', 100)} < 20 + {u('asn', 'cov', 75)} AND {u("concat(a, '|', scan)", 'drop', 100)} >= 3""",
    )
    made["responses"] = (
        ("replies_sent", "device"),
        f"""SELECT cast(scan AS int) AS scan, cast(family AS int) AS family, addr, a AS addr_key, cast(recv_s AS bigint) AS recv_s, CASE WHEN {u('a', 'miss', 1000)} < 1 THEN NULL ELSE engine_id END AS engine_id,
            cast(CASE WHEN boots = 0 THEN 0 WHEN scan = 2 AND rebooted THEN boots + 1 ELSE boots END AS bigint) AS boots,
            cast(CASE WHEN boots = 0 THEN 0 WHEN future THEN 2147480000
                ELSE recv_s - CASE WHEN scan = 2 AND rebooted THEN {SCAN_2} - 7200 ELSE boot_epoch END + {jitter} END AS bigint) AS engine_time
        FROM (SELECT r.a, r.scan, r.family, r.addr, r.recv_s, v.engine_id, v.boots, v.boot_epoch, v.rebooted, v.future FROM {{replies_sent}} r JOIN {{device}} v ON v.device = r.answering) x""",
    )
    # some addresses answer again a little later, a part of them as another device
    made["reply_packets"] = (
        ("responses",),
        f"""SELECT scan, family, addr, addr_key, recv_s, engine_id, boots, engine_time FROM {{responses}}
        UNION ALL SELECT scan, family, addr, addr_key, recv_s + 1 + {u('addr_key', 'again', 5)}, CASE WHEN {u('addr_key', 'other', 100)} < 30 AND engine_id IS NOT NULL THEN concat(substr(engine_id, 1, 10), 'ffffffff') ELSE engine_id END,
            boots + {u('addr_key', 'other', 2)}, engine_time + 7 FROM {{responses}} WHERE {u('addr_key', 'repeat', 1000)} < 60""",
    )
    made["truth"] = (("address", "device"), "SELECT p.a AS addr_key, p.d AS device, p.asn AS asn, v.vendor_no AS vendor_no FROM {address} p JOIN {device} v ON v.device = p.d")
    made["router_tags"] = (
        ("address",),
        f"""SELECT 'topology' AS source, family, addr FROM {{address}} WHERE {u('d', 'rt', 100)} < 45 AND {u('a', 'tA', 100)} < 80
        UNION ALL SELECT 'traceroute', family, addr FROM {{address}} WHERE {u('d', 'rt', 100)} < 45 AND {u('a', 'tB', 100)} < 20
        UNION ALL SELECT 'hoplist', family, addr FROM {{address}} WHERE family = 6 AND {u('d', 'rt', 100)} < 60 AND {u('a', 'tC', 100)} < 70""",
    )
    brands = f"SELECT DISTINCT p_brand AS vendor, {q.brand_number('p_brand')} AS n FROM {{part}}"
    made["mac_registry"] = (("part",), f"SELECT substr(md5(concat('oui', '|', n)), 1, 6) AS prefix, vendor FROM ({brands}) x")
    made["enterprise_registry"] = (("part",), f"SELECT 9000 + n AS enterprise, vendor FROM ({brands}) x UNION ALL SELECT 8999, 'software-agent'")
    made["special_v4"] = ((), " UNION ALL ".join(f"SELECT cast({a} AS bigint) AS lo, cast({b} AS bigint) AS hi, '{why}' AS reason" for a, b, why in special_ranges()))
    made["prefixes"] = (
        ("supplier", "address", "sizes"),
        f"""SELECT 4 AS family, {V4_BASE} + s_suppkey * {AS_SPAN} AS base, cast(NULL AS string) AS base6, 14 AS length, s_suppkey AS asn FROM {{supplier}}
        UNION ALL SELECT 6, NULL, concat('2001:0db8:', printf('%04x', s_suppkey), '::'), 48, s_suppkey FROM {{supplier}}
        UNION ALL SELECT 4, net * 256, NULL, 24, (asn + 1) % ns FROM (SELECT DISTINCT v4 {d} 256 AS net, asn FROM {{address}} WHERE family = 4) x CROSS JOIN {{sizes}} z WHERE {u('net', 'more', 100)} < 3""",
    )
    made["as_region"] = (
        ("supplier", "nation", "region"),
        "SELECT s.s_suppkey AS asn, n.n_name AS country, r.r_name AS region FROM {supplier} s JOIN {nation} n ON n.n_nationkey = s.s_nationkey JOIN {region} r ON r.r_regionkey = n.n_regionkey",
    )
    made["ptr"] = (
        ("address",),
        f"""SELECT addr, family, a AS addr_key, CASE WHEN {u('asn', 'odd', 100)} < 30 THEN concat('ip', a % 8, '.as', asn, '.example.net') ELSE concat('if', a % 8, '.r', d, '.as', asn, '.example.net') END AS name
        FROM {{address}} WHERE {u('a', 'ptr', 100)} < 60""",
    )
    made["name_rules"] = (("supplier",), f"SELECT concat('as', s_suppkey, '.example.net') AS suffix, '^[a-z]+[0-9]+[.](r[0-9]+)[.]' AS regex, cast(50 + {u('s_suppkey', 'ppv', 51)} AS double) / 100 AS ppv FROM {{supplier}}")
    counter = lambda salt, share, fam: f"""SELECT CASE WHEN {u('a', 'cs', 100)} < 85 THEN concat('d', d) ELSE concat('a', a) END AS ref_set_id, addr, a AS addr_key FROM {{address}}
        WHERE family = {fam} AND {u('d', salt, 100)} < {share}"""  # noqa: E731
    made["counter_sets_v4"] = (("address",), counter("cnt", 35, 4))
    made["fragid_sets_v6"] = (("address",), counter("frag", 50, 6))
    made["ipid_samples"] = (
        ("lineitem", "address"),
        f"""SELECT addr_key, t, CASE WHEN {u('d', 'ctr', 100)} < 70 THEN ({u('d', 'off', 65536)} + t * (1 + {u('d', 'vel', 50)})) % 65536
            ELSE {u("concat(addr_key, '|', line, '|', part)", 'noise', 65536)} END AS ipid, asn
        FROM (SELECT l.l_orderkey AS addr_key, l.l_linenumber AS line, l.l_partkey AS part, {q.days('l.l_shipdate')} AS t, p.d AS d, p.asn AS asn FROM {{lineitem}} l JOIN {{address}} p ON p.a = l.l_orderkey) x""",
    )
    made["fragid_samples"] = (
        ("lineitem", "address"),
        f"""SELECT addr_key, t, CASE WHEN {u('d', 'fctr', 100)} < 70 THEN ({u('d', 'foff', 1 << 32)} + t * (1 + {u('d', 'fvel', 1000000)})) % {1 << 32}
            ELSE {u("concat(addr_key, '|', line, '|', part)", 'fnoise', 1 << 32)} END AS ipid, asn
        FROM (SELECT l.l_orderkey AS addr_key, l.l_linenumber AS line, l.l_partkey AS part, {q.days('l.l_shipdate')} AS t, p.d AS d, p.asn AS asn FROM {{lineitem}} l JOIN {{address}} p ON p.a = l.l_orderkey WHERE p.family = 6) x""",
    )
    made["active_outcome"] = (
        ("device",),
        f"""SELECT device, CASE WHEN act < 841 THEN 'none' WHEN act < 890 THEN 'guess' ELSE 'exact' END AS outcome,
            CASE WHEN act < 841 THEN NULL WHEN act < 890 THEN concat('Brand#', vendor_no % 25 + 1) ELSE concat('Brand#', vendor_no) END AS vendor,
            CASE WHEN act < 890 THEN NULL ELSE concat('os-', act % 7) END AS os
        FROM (SELECT device, vendor_no, {u('device', 'act', 1000)} AS act FROM {{device}}) x""",
    )
    made["legacy_responders"] = (
        ("address",),
        f"SELECT 'first' AS service, addr FROM {{address}} WHERE {u('a', 'leg1', 100)} < 8 UNION ALL SELECT 'second', addr FROM {{address}} WHERE {u('a', 'leg2', 100)} < 6",
    )
    made["packets"] = (("lineitem",), f"SELECT l_orderkey AS req, {q.seconds('l_shipdate')} AS recv_s, cast(100 + l_quantity AS bigint) AS bytes FROM {{lineitem}}")
    made["interfaces"] = (
        ("address", "device"),
        f"""SELECT p.d AS device, p.addr AS addr, concat(v.mac_prefix, {md('p.a', 'if', 6)}) AS mac FROM {{address}} p JOIN {{device}} v ON v.device = p.d
        UNION ALL SELECT device, NULL, substr(engine_id, 11, 12) FROM {{device}} WHERE length(engine_id) = 22 AND substr(engine_id, 9, 2) = '03'""",
    )
    made["event_replies"] = (
        ("events", "device", "sizes"),
        f"""SELECT x.event_id AS event_id, x.ts AS ts, x.recv_s AS recv_s, x.addr AS addr, v.engine_id AS engine_id, 1 + x.day {d} x.p AS boots, x.recv_s - 1704067200 - 86400 * (x.p * (x.day {d} x.p)) AS engine_time
        FROM (SELECT event_id, ts, user_id AS addr, {q.seconds('ts')} AS recv_s, ({q.seconds('ts')} - 1704067200) {d} 86400 AS day, 5 + {u('user_id', 'per', 10)} AS p,
            CASE WHEN {u('event_id', 'nat', 1000)} < 1 THEN user_id + 1 ELSE user_id END % z.nc AS answering FROM {{events}} CROSS JOIN {{sizes}} z) x
        JOIN {{device}} v ON v.device = x.answering""",
    )
    return made


_SPARK, _DUCK = _definitions(Dialect(True)), _definitions(Dialect(False))


def given(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Relations that many queries read, or that cost a join to derive: stored once a session and directory.
STORED = ("device", "address", "responses", "reply_packets", "truth", "router_tags", "ptr", "ipid_samples", "fragid_samples", "event_replies")


def relation(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table or derived relation: stored, or lazily derived."""
    if name in GIVEN:
        return given(spark, sf_dir, name)
    reads, text = _SPARK[name]
    derived = lambda: spark.sql(text, **{r: relation(spark, sf_dir, r) for r in reads})
    if name in STORED and (path := stored_path(spark, sf_dir, name, derived)):
        return spark.read.parquet(path)
    return derived()


def stored(spark: SparkSession, sf_dir: str, name: str) -> str:
    """The folder of a stored relation, for readers of files."""
    relation(spark, sf_dir, name)
    path = stored_path(spark, sf_dir, name, lambda: relation(spark, sf_dir, name))
    if not path:
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return path


def oracle_relations(*names: str) -> str:
    """The WITH entries (without WITH) that define the relations and what they read, for DuckDB."""
    order: list[str] = []

    def visit(name: str) -> None:
        if name in GIVEN or name in order:
            return
        for r in _DUCK[name][0]:
            visit(r)
        order.append(name)

    for name in names:
        visit(name)
    return ",\n".join(f"{n} AS MATERIALIZED ({_DUCK[n][1].format(**{r: r for r in _DUCK[n][0]})})" for n in order)
