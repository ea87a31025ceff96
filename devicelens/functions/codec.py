"""Engine identifiers: decoding, rendering and bit weights, as native expressions over their hexadecimal form."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

AGENT_ENTERPRISE = 8999
#: Format codes of the public standard for engine identifiers.
FORMATS = {"01": "ipv4", "02": "ipv6", "03": "mac", "04": "text", "05": "octets"}


def number(hexadecimal: Column) -> Column:
    return F.conv(hexadecimal, 16, 10).cast("bigint")


def decode(engine_id: Column, agent: int = AGENT_ENTERPRISE) -> Column:
    """struct(conforming, enterprise, format, data, n_bytes) of an identifier in lower-case hex; never raises.

    A clear top bit means non-conforming: no enterprise, all is data. Fewer than 5 bytes are 'truncated'; null or empty is 'missing'.
    """
    empty = F.coalesce(F.length(engine_id), F.lit(0)) == 0
    conforming = F.substring(engine_id, 1, 1) >= "8"
    long = F.length(engine_id) >= 10
    enterprise = F.when(conforming & long, number(F.substring(engine_id, 1, 8)) - F.lit(1 << 31))
    code = F.substring(engine_id, 9, 2)
    kind = F.when(empty, "missing").when(~conforming, "nonconforming").when(~long, "truncated")
    for value, name in FORMATS.items():
        kind = kind.when(code == value, name)
    kind = kind.when(code < "80", "reserved").when(enterprise == agent, "agent").otherwise("vendor")
    data = F.when(empty, None).when(~conforming, engine_id).when(~long, F.substring(engine_id, 9, 1 << 20)).otherwise(F.substring(engine_id, 11, 1 << 20))
    return F.struct(
        F.coalesce(conforming, F.lit(False)).alias("conforming"), enterprise.alias("enterprise"), kind.alias("format"), data.alias("data"), (F.coalesce(F.length(engine_id), F.lit(0)) / 2).cast("int").alias("n_bytes")
    )


def with_decoded(df: DataFrame, column: str = "engine_id") -> DataFrame:
    return df.withColumn("id", decode(F.col(column)))


def render(decoded: Column) -> Column:
    """The data part in readable form: aa:bb:.., dotted, hextets, text, else hex."""
    data, kind = decoded["data"], decoded["format"]
    pairs = F.regexp_replace(F.regexp_replace(data, "(..)", "$1:"), ":$", "")
    dotted = F.concat_ws(".", *(number(F.substring(data, 1 + 2 * k, 2)).cast("string") for k in range(4)))
    hextets = F.regexp_replace(F.regexp_replace(data, "(....)", "$1:"), ":$", "")
    text = F.decode(F.unhex(data), "utf-8")
    return F.when(kind == "mac", pairs).when((kind == "ipv4") & (F.length(data) == 8), dotted).when((kind == "ipv6") & (F.length(data) == 32), hextets).when(kind == "text", text).otherwise(data)


def ones(data: Column) -> Column:
    """Bits set in a hex string, by chunks that fit a signed 64-bit number."""
    chunks = F.filter(F.transform(F.sequence(F.lit(0), F.lit(9)), lambda k: F.substring(data, k * 14 + 1, F.lit(14))), lambda x: x != "")
    return F.aggregate(chunks, F.lit(0).cast("bigint"), lambda s, x: s + F.bit_count(number(x)))


def rel_hamming(data: Column) -> Column:
    """Share of ones among the bits of a hex string of up to 70 bytes; null for none."""
    return F.when(F.length(data) > 0, ones(data) / (F.length(data) * 4))


def ip4_to_long(addr: Column) -> Column:
    return sum((F.split_part(addr, F.lit("."), F.lit(k + 1)).cast("bigint") * (1 << 8 * (3 - k)) for k in range(1, 4)), F.split_part(addr, F.lit("."), F.lit(1)).cast("bigint") * (1 << 24))


def long_to_ip4(x: Column) -> Column:
    return F.concat_ws(".", *(F.shiftright(x, 8 * k).bitwiseAND(255).cast("string") for k in (3, 2, 1, 0)))


def prefix_of(x: Column, length: int) -> Column:
    """The network of an IPv4 number."""
    return x - x % (1 << (32 - length))


def in_ranges(x: Column, ranges: list[tuple[int, int, str]]) -> Column:
    """Whether a number lies in one of the ranges; literals, so that it is pushed to a scan."""
    found = F.lit(False)
    for low, high, _ in ranges:
        found = found | x.between(low, high)
    return found


def mac_normalise(mac: Column) -> Column:
    return F.lower(F.regexp_replace(mac, "[^0-9A-Fa-f]", ""))
