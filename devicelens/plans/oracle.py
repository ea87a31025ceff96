"""Relations of the oracle: the methods once more, in DuckDB SQL, by other plans (joins where Spark pivots, subqueries where Spark joins)."""

from __future__ import annotations

import re

from devicelens.sources import fixture

SPECIAL = " OR ".join(f"ip BETWEEN {a} AND {b}" for a, b, _ in fixture.special_ranges())


def decoded(column: str, alias: str = "") -> str:
    """Columns of a decoded identifier."""
    c = column
    return f"""CASE WHEN substr({c}, 1, 1) >= '8' AND length({c}) >= 10 THEN ('0x' || substr({c}, 1, 8))::BIGINT - 2147483648 END AS {alias}enterprise,
        CASE WHEN coalesce({c}, '') = '' THEN 'missing' WHEN substr({c}, 1, 1) < '8' THEN 'nonconforming' WHEN length({c}) < 10 THEN 'truncated'
            WHEN substr({c}, 9, 2) = '01' THEN 'ipv4' WHEN substr({c}, 9, 2) = '02' THEN 'ipv6' WHEN substr({c}, 9, 2) = '03' THEN 'mac' WHEN substr({c}, 9, 2) = '04' THEN 'text'
            WHEN substr({c}, 9, 2) = '05' THEN 'octets' WHEN substr({c}, 9, 2) < '80' THEN 'reserved' WHEN substr({c}, 1, 8) = printf('%08x', 2147483648 + 8999) THEN 'agent' ELSE 'vendor' END AS {alias}format,
        CASE WHEN coalesce({c}, '') = '' THEN NULL WHEN substr({c}, 1, 1) < '8' THEN {c} WHEN length({c}) < 10 THEN substr({c}, 9) ELSE substr({c}, 11) END AS {alias}data"""


def alias_sets(name: str, key: str, source: str = "valid") -> str:
    return f"""SELECT min(addr_key) AS set_id, min(id1) AS engine_id, count(*) AS n, count(*) FILTER (family = 4) AS n4, count(*) FILTER (family = 6) AS n6, min(boots1) AS boots, min(r1) AS reboot_min, max(r1) AS reboot_max,
        CASE WHEN count(*) FILTER (family = 6) = 0 THEN 'v4' WHEN count(*) FILTER (family = 4) = 0 THEN 'v6' ELSE 'dual' END AS class FROM {source} GROUP BY {key}"""


CANON = "id1, boots1, boots2, r1 // 20, r2 // 20"
LIB: dict[str, str] = {
    "paired": """SELECT coalesce(a.family, b.family) AS family, coalesce(a.addr, b.addr) AS addr, coalesce(a.addr_key, b.addr_key) AS addr_key, a.engine_id AS id1, b.engine_id AS id2, a.boots AS boots1, b.boots AS boots2,
        a.engine_time AS t1, b.engine_time AS t2, a.recv_s - a.engine_time AS r1, b.recv_s - b.engine_time AS r2, a.addr IS NOT NULL AS in1, b.addr IS NOT NULL AS in2
        FROM (SELECT * FROM responses WHERE scan = 1) a FULL JOIN (SELECT * FROM responses WHERE scan = 2) b ON a.addr = b.addr""",
    "early": """SELECT *, CASE WHEN coalesce(id1, id2) IS NULL THEN 1 WHEN NOT (in1 AND in2) OR id1 IS NULL OR id2 IS NULL THEN 2 WHEN id1 <> id2 THEN 3 WHEN length(id1) < 8 THEN 4 END AS early FROM paired""",
    "dec": f"SELECT *, {decoded('id1')} FROM early",
    "promisc": "SELECT data FROM dec WHERE early IS NULL AND enterprise IS NOT NULL AND data <> '' GROUP BY data HAVING count(DISTINCT enterprise) > 1",
    "flags": f"""SELECT *, enterprise IS NOT NULL AND data IN (SELECT data FROM promisc) AS f5,
        coalesce(format = 'ipv4' AND length(data) = 8 AND (SELECT bool_or({SPECIAL}) FROM (SELECT TRY_CAST('0x' || data AS BIGINT) AS ip)), false) AS f6,
        format = 'mac' AND substr(data, 1, 6) NOT IN (SELECT prefix FROM mac_registry) AS f7,
        coalesce(boots1, 0) <= 0 OR coalesce(boots2, 0) <= 0 OR coalesce(t1, 0) <= 0 OR coalesce(t2, 0) <= 0 AS f8, coalesce(r1 < 0 OR r2 < 0, false) AS f9, boots1 IS DISTINCT FROM boots2 AS f10, coalesce(abs(r1 - r2) > 10, true) AS f11
        FROM dec""",
    "stepped": "SELECT *, CASE WHEN early IS NOT NULL THEN early WHEN f5 THEN 5 WHEN f6 THEN 6 WHEN f7 THEN 7 WHEN f8 THEN 8 WHEN f9 THEN 9 WHEN f10 THEN 10 WHEN f11 THEN 11 END AS step FROM flags",
    "valid": "SELECT * FROM stepped WHERE step IS NULL",
    "sets": alias_sets("sets", CANON),
    "members": f"SELECT min(addr_key) OVER (PARTITION BY {CANON}) AS set_id, family, addr, addr_key, id1 FROM valid",
    "vendors": f"""SELECT s.*, d.format, CASE WHEN d.format = 'mac' AND m.vendor IS NOT NULL THEN m.vendor WHEN e.vendor IS NOT NULL THEN e.vendor ELSE 'unknown' END AS vendor,
        CASE WHEN d.format = 'mac' AND m.vendor IS NOT NULL THEN 'high' WHEN e.vendor IS NOT NULL THEN 'medium' ELSE 'none' END AS confidence, m.vendor AS mac_vendor, e.vendor AS enterprise_vendor
        FROM sets s JOIN (SELECT engine_id AS eid, {decoded('engine_id')} FROM (SELECT DISTINCT engine_id FROM sets)) d ON d.eid = s.engine_id
        LEFT JOIN mac_registry m ON d.format = 'mac' AND m.prefix = substr(d.data, 1, 6) LEFT JOIN enterprise_registry e ON e.enterprise = d.enterprise""",
    "addr_as": """SELECT a.*, p.asn FROM (SELECT addr, family, addr_key, CASE WHEN family = 4 THEN split_part(addr, '.', 1)::BIGINT * 16777216 + split_part(addr, '.', 2)::BIGINT * 65536 + split_part(addr, '.', 3)::BIGINT * 256
        + split_part(addr, '.', 4)::BIGINT END AS ip FROM (SELECT addr, family, a AS addr_key FROM address)) a JOIN LATERAL (SELECT asn FROM prefixes p WHERE p.family = a.family AND
        CASE WHEN a.family = 4 THEN a.ip BETWEEN p.base AND p.base + (1::BIGINT << (32 - p.length)) - 1 ELSE starts_with(a.addr, p.base6) END ORDER BY p.length DESC LIMIT 1) p ON true""",
    "set_as": """SELECT set_id, asn FROM (SELECT m.set_id, x.asn, row_number() OVER (PARTITION BY m.set_id ORDER BY count(*) DESC, x.asn) AS k FROM members m JOIN addr_as x USING (addr) GROUP BY m.set_id, x.asn) WHERE k = 1""",
    "router_any": "SELECT DISTINCT m.set_id FROM members m JOIN router_tags t USING (addr)",
    "router_two": "SELECT DISTINCT m.set_id FROM members m JOIN router_tags t USING (addr) WHERE t.source IN ('topology', 'traceroute')",
    "routers": "SELECT v.*, a.asn, g.region, g.country FROM vendors v JOIN router_two r USING (set_id) JOIN set_as a USING (set_id) JOIN as_region g USING (asn)",
    "as_vendor": "SELECT asn, region, vendor, count(*) AS n FROM routers GROUP BY ALL",
    "as_total": "SELECT asn, region, sum(n)::BIGINT AS routers, count(*) AS vendors, max(n) AS top FROM as_vendor GROUP BY ALL",
    "names": """SELECT addr, family, suffix || '/' || regexp_extract(name, regex, 1) AS set_id FROM (SELECT p.*, r.* FROM ptr p JOIN name_rules r ON ends_with(p.name, '.' || r.suffix))
        WHERE ppv >= 0.8 AND regexp_extract(name, regex, 1) <> ''""",
    "coverage": """SELECT x.asn, count(*) AS routers, count(*) FILTER (x.addr IN (SELECT addr FROM responses)) AS responding FROM addr_as x WHERE x.family = 4 AND x.addr IN (SELECT addr FROM router_tags WHERE family = 4) GROUP BY x.asn""",
}


def oracle(text: str) -> str:
    """The text with every relation it needs defined in front, each once and after what it reads."""
    known = set(LIB) | set(fixture._DUCK)
    order: list[str] = []

    def needs(sql: str) -> list[str]:
        return [w for w in dict.fromkeys(re.findall(r"(?:FROM|JOIN|,)\s+([a-z_0-9]+)", sql)) if w in known]

    def visit(name: str) -> None:
        if name in order:
            return
        for n in needs(LIB[name]) if name in LIB else [r for r in fixture._DUCK[name][0] if r in known]:
            if n != name:
                visit(n)
        order.append(name)

    for n in needs(text):
        visit(n)
    parts = [f"{n} AS MATERIALIZED ({LIB[n] if n in LIB else fixture._DUCK[n][1].format(**{r: r for r in fixture._DUCK[n][0]})})" for n in order]
    return ("WITH " + ",\n".join(parts) + "\n" if parts else "") + text
