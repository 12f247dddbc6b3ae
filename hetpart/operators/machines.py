"""Fleets of unequal machines: at most a few thousand rows, kept on the driver."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "machine int, mem double, c_node double, c_edge double, c_com double, kind string"
#: Memory of a vertex and of an edge.
M_NODE, M_EDGE = 1.0, 2.0


@dataclass(frozen=True)
class Machine:
    mem: float
    c_node: float
    c_edge: float
    c_com: float
    kind: str = "normal"


@dataclass(frozen=True)
class Fleet:
    machines: tuple[Machine, ...]
    m_node: float = M_NODE
    m_edge: float = M_EDGE

    def __len__(self) -> int:
        return len(self.machines)

    def column(self, name: str) -> list[float]:
        return [getattr(m, name) for m in self.machines]

    def df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(i, float(m.mem), float(m.c_node), float(m.c_edge), float(m.c_com), m.kind) for i, m in enumerate(self.machines)], SCHEMA)

    def values(self, name: str) -> Column:
        """An attribute by machine, as an array expression."""
        return F.array(*[F.lit(float(x)) for x in self.column(name)])

    def with_work(self, node: float, edge: float) -> Fleet:
        """Costs for an algorithm that does so much work for each vertex and edge."""
        return replace(self, machines=tuple(replace(m, c_node=m.c_node * node, c_edge=m.c_edge * edge) for m in self.machines))

    def with_memory(self, factor: float) -> Fleet:
        return replace(self, machines=tuple(replace(m, mem=math.ceil(m.mem * factor)) for m in self.machines))

    def subset(self, which: list[int]) -> Fleet:
        return replace(self, machines=tuple(self.machines[i] for i in which))


def two_type(n_super: int, n_normal: int, super_: Machine, normal: Machine) -> Fleet:
    return Fleet((replace(super_, kind="super"),) * n_super + (replace(normal, kind="normal"),) * n_normal)


#: Machine kinds of the experiments, and the edges their memory was meant for.
SMALL = (Machine(1e7, 10, 15, 15), Machine(3e6, 5, 10, 10), 33_099_465)
LARGE = (Machine(1e8, 10, 15, 15), Machine(3e7, 5, 10, 10), 117_185_083)


def scaled(m: Machine, edges: int, meant: int) -> Machine:
    return replace(m, mem=math.ceil(m.mem * edges / meant))


def small(edges: int, n_super: int = 10, n_normal: int = 20) -> Fleet:
    a, b, meant = SMALL
    return two_type(n_super, n_normal, scaled(a, edges, meant), scaled(b, edges, meant))


def large(edges: int) -> Fleet:
    a, b, meant = LARGE
    return two_type(20, 80, scaled(a, edges, meant), scaled(b, edges, meant))


def homogeneous(edges: int, p: int = 30) -> Fleet:
    return two_type(0, p, SMALL[0], replace(scaled(SMALL[1], edges, SMALL[2]), mem=math.ceil(2 * 3e6 * edges / SMALL[2])))


def share_super(edges: int, p: int) -> Fleet:
    """p machines, a third of them super."""
    return small(edges, p // 3, p - p // 3)


def typed(edges: int, q: int, p: int = 30) -> Fleet:
    """q kinds of machines: each kind beyond the first takes a sixth of the machines (five of
    thirty), the last ones; kind t is enlarged by 1 + t / 4."""
    base, per, out = scaled(SMALL[1], edges, SMALL[2]), max(1, p // 6), []
    for i in range(p):
        kind = max(0, (i - (p - per * (q - 1))) // per + 1)
        f = 1 + 0.25 * kind
        out.append(Machine(math.ceil(base.mem * 2 * f), base.c_node * f, base.c_edge * f, base.c_com * f, f"type{kind}"))
    return Fleet(tuple(out))


def nine(edges: int) -> Fleet:
    """Three large slow machines and six small fast ones."""
    per = edges / 9
    return two_type(3, 6, Machine(math.ceil(per * 9), 10, 15, 15), Machine(math.ceil(per * 3.6), 5, 10, 10))


#: The running example's three machines.
THREE = Fleet((Machine(7, 0, 1, 1), Machine(7, 0, 2, 2), Machine(5, 0, 1, 1)))


def quantify(bench: DataFrame, attr_factor: int = 1) -> DataFrame:
    """Relative rates from raw measurements (machine, mem_gb, fp_ns, fp2_ns, co_ns), all
    integers: memory units of a quarter gigabyte over the sizes' common divisor, compute
    times over that of the one-operation times, transfer of 4 KB likewise."""
    rows = bench.agg(F.collect_set("mem_gb").alias("m"), F.collect_set("fp_ns").alias("f")).first()  # values of p rows
    mem_gcd, fp_gcd = math.gcd(*rows["m"]), math.gcd(*rows["f"])
    return bench.select("machine", (F.col("mem_gb") * 250_000_000 / mem_gcd).alias("mem"), F.lit(attr_factor / mem_gcd).alias("m_node"), F.lit(2.0 / mem_gcd).alias("m_edge"), (F.col("fp_ns") * attr_factor / fp_gcd).alias("c_node"), (F.col("fp2_ns") / fp_gcd).alias("c_edge"), (F.col("co_ns") / (1024 * fp_gcd)).alias("c_com"))
