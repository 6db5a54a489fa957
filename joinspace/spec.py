"""Join queries: relations over shared attributes, and the workloads on the given tables."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class Relation:
    """keys, coords and cats map a name to an SQL expression over the table's columns. A coordinate has one owner."""

    name: str
    table: str
    keys: dict[str, str]
    coords: dict[str, str] = field(default_factory=dict)
    cats: dict[str, str] = field(default_factory=dict)
    where: str | None = None

    def __hash__(self) -> int:
        return hash(self.name)


@dataclass(frozen=True)
class JoinSpec:
    name: str
    relations: tuple[Relation, ...]

    @property
    def coords(self) -> list[str]:
        return [c for r in self.relations for c in r.coords]

    @property
    def cats(self) -> list[str]:
        return [c for r in self.relations for c in r.cats]

    def edges(self) -> dict[str, frozenset[str]]:
        return {r.name: frozenset(r.keys) for r in self.relations}

    def owner(self, coord: str) -> Relation:
        return next(r for r in self.relations if coord in r.coords or coord in r.cats)


def _lineitem(name: str, keys: dict, coords: dict, cats: dict | None = None) -> Relation:
    return Relation(name, "lineitem", keys, coords, cats or {})


OK, CK, NK, SK, PK = "l_orderkey", "c_custkey", "c_nationkey", "s_suppkey", "p_partkey"

WORKLOADS: dict[str, JoinSpec] = {
    s.name: s
    for s in (
        JoinSpec("w1", (
            _lineitem("lineitem", {"ok": "l_orderkey", "pk": "l_partkey", "sk": "l_suppkey"}, {"quantity": "l_quantity"}, {"returnflag": "l_returnflag"}),
            Relation("orders", "orders", {"ok": "o_orderkey", "ck": "o_custkey"}, {"totalprice": "o_totalprice"}),
            Relation("customer", "customer", {"ck": "c_custkey"}, {"acctbal": "c_acctbal"}, {"segment": "c_mktsegment"}),
            Relation("part", "part", {"pk": "p_partkey"}, {"retailprice": "p_retailprice"}, {"brand": "p_brand"}),
            Relation("supplier", "supplier", {"sk": "s_suppkey"}, {"s_acctbal": "s_acctbal"}),
        )),
        JoinSpec("w2", (
            _lineitem("a", {"ok": "l_orderkey"}, {"price_a": "l_extendedprice"}),
            _lineitem("b", {"ok": "l_orderkey"}, {"price_b": "l_extendedprice"}),
        )),
        JoinSpec("w3", (
            _lineitem("lineitem", {"sk": "l_suppkey"}, {"quantity": "l_quantity"}),
            Relation("supplier", "supplier", {"sk": "s_suppkey", "nk": "s_nationkey"}, {"s_acctbal": "s_acctbal"}),
            Relation("customer", "customer", {"ck": "c_custkey", "nk": "c_nationkey"}, {"c_acctbal": "c_acctbal"}),
            Relation("orders", "orders", {"ck": "o_custkey"}, {"totalprice": "o_totalprice"}),
        )),
        JoinSpec("w4", (
            Relation("customer", "customer", {"ck": "c_custkey", "nk": "c_nationkey"}, {"c_acctbal": "c_acctbal"}),
            Relation("supplier", "supplier", {"sk": "s_suppkey", "nk": "s_nationkey"}, {"s_acctbal": "s_acctbal"}),
            _lineitem("lineitem", {"ok": "l_orderkey", "sk": "l_suppkey"}, {"quantity": "l_quantity"}),
            Relation("orders", "orders", {"ok": "o_orderkey", "ck": "o_custkey"}),
        )),
        JoinSpec("w4t", (
            Relation("pairs", "(SELECT DISTINCT o_custkey, l_suppkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey)", {"ck": "o_custkey", "sk": "l_suppkey"}),
            Relation("customer", "customer", {"ck": "c_custkey", "nk": "c_nationkey"}, {"c_acctbal": "c_acctbal"}),
            Relation("supplier", "supplier", {"sk": "s_suppkey", "nk": "s_nationkey"}, {"s_acctbal": "s_acctbal"}),
        )),
        JoinSpec("w5", (
            Relation("a", "events", {"user": "user_id"}, {"value_a": "value"}, {"type_a": "event_type"}),
            Relation("b", "events", {"user": "user_id"}, {"value_b": "value"}, {"type_b": "event_type"}),
        )),
        JoinSpec("w6", (
            Relation("customer", "customer", {"ck": "c_custkey", "nk": "c_nationkey"}, {"acctbal": "c_acctbal"}),
            Relation("events", "events", {"ck": "user_id"}, {"value": "value"}, {"event_type": "event_type"}),
            Relation("nation", "nation", {"nk": "n_nationkey"}, {}, {"nation": "n_name"}),
            Relation("orders", "orders", {"ck": "o_custkey", "ok": "o_orderkey"}, {"totalprice": "o_totalprice"}),
            _lineitem("lineitem", {"ok": "l_orderkey"}, {"quantity": "l_quantity"}, {"returnflag": "l_returnflag"}),
        )),
        JoinSpec("w7", (
            _lineitem("lineitem", {"ok": "l_orderkey"}, {"quantity": "l_quantity"}, {"returnflag": "l_returnflag"}),
            Relation("orders", "orders", {"ok": "o_orderkey", "ck": "o_custkey"}, {"totalprice": "o_totalprice"}, {"priority": "o_orderpriority"}),
            Relation("customer", "customer", {"ck": "c_custkey"}, {"acctbal": "c_acctbal"}, {"segment": "c_mktsegment"}),
        )),
        JoinSpec("w8", (
            Relation("orders", "orders", {"ck": "o_custkey"}, {"totalprice": "o_totalprice"}),
            Relation("customer", "customer", {"ck": "c_custkey"}, {"acctbal": "c_acctbal"}, {"segment": "c_mktsegment"}),
        )),
        JoinSpec("w9", (
            Relation("customer", "customer", {"nk": "c_nationkey"}, {"c_acctbal": "c_acctbal"}),
            Relation("nation", "nation", {"nk": "n_nationkey"}, {}, {"region": "n_regionkey"}),
            Relation("supplier", "supplier", {"nk": "s_nationkey"}, {"s_acctbal": "s_acctbal"}),
        )),
        JoinSpec("w10", (
            Relation("documents", "documents", {"doc": "doc_id"}, {"n_chars": "n_chars"}, {"lang": "lang", "source": "source"}),
            Relation("labels", "labels", {"doc": "doc_id"}, {}, {"quality": "quality", "toxic": "toxic"}),
        )),
        JoinSpec("w11", (_lineitem("lineitem", {}, {"quantity": "l_quantity", "discount": "l_discount", "tax": "l_tax"}),)),
        JoinSpec("w12", (
            Relation("nation", "nation", {"rk": "n_regionkey", "nk": "n_nationkey"}, {"nk": "n_nationkey"}),
            Relation("region", "region", {"rk": "r_regionkey"}, {"rk": "r_regionkey"}, {"r_name": "r_name"}),
        )),
    )
}
