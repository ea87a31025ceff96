"""What the registered queries read: relations and the intermediate results that several methods share, as lazy plans."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from devicelens.operators import alias, fingerprint, funnel, netstats, tags
from devicelens.sources.fixture import relation


class Inputs:
    """Lazy plans over one directory of tables; every property is built when first asked for."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir
        self._made: dict[str, DataFrame] = {}

    def __getattr__(self, name: str) -> DataFrame:
        if name.startswith("_"):
            raise AttributeError(name)
        if name not in self._made:
            make = getattr(Inputs, f"make_{name}", None)
            self._made[name] = make(self) if make else relation(self.spark, self.sf_dir, name)
        return self._made[name]

    def make_merged(self) -> DataFrame:
        return funnel.two_scans(self.reply_packets)

    def make_flags(self) -> DataFrame:
        return funnel.flagged(self.merged, self.mac_registry, self.enterprise_registry)

    def make_valid(self) -> DataFrame:
        return funnel.run(self.flags)

    def make_sets(self) -> DataFrame:
        return alias.resolve(self.valid)

    def make_members(self) -> DataFrame:
        return alias.members(self.valid)

    def make_vendors(self) -> DataFrame:
        return fingerprint.set_vendor(self.sets, self.mac_registry, self.enterprise_registry)

    def make_addr_as(self) -> DataFrame:
        return netstats.lpm(self.address.select("addr", "family", F.col("a").alias("addr_key")), self.prefixes)

    def make_set_as(self) -> DataFrame:
        return netstats.set_asn(self.members, self.addr_as)

    def make_router_two(self) -> DataFrame:
        return tags.router_sets(self.members, self.router_tags, sources=("topology", "traceroute"))

    def make_routers(self) -> DataFrame:
        return self.vendors.join(self.router_two, "set_id", "left_semi").join(self.set_as, "set_id").join(self.as_region, "asn")

    def make_as_vendor(self) -> DataFrame:
        return netstats.as_vendor(self.routers)

    def make_coverage(self) -> DataFrame:
        return netstats.coverage(self.router_tags, self.responses, self.addr_as)
