"""SQL surface: certificates and separators as table functions, local connectivity as a function, graphs as views."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from certgraph.functions.graph_kernels import OnlineCertificate, component_count, graph_of, is_k_connected, layered_rows, local_connectivity, pieces_without_each_vertex


class CertificateEdges:
    """certificate_edges(TABLE(e) PARTITION BY g ORDER BY (seq), k, method): the kept edges of each graph.

    The table's last three columns are seq, u, v.
    """

    def __init__(self):
        self.rows, self.k, self.method = [], 1, "layered"

    def eval(self, row, k, method):
        *_, seq, u, v = row
        self.rows.append((int(seq), min(u, v), max(u, v)))
        self.k, self.method = k, method

    def terminate(self):
        if self.method == "online":
            c = OnlineCertificate(self.k)
            for e in sorted(self.rows):
                c.offer(e)
            for s, u, v in c.kept:
                yield s, u, v, None
        else:
            yield from layered_rows(self.rows, self.k)


class SmallSeparators:
    """k_separators(TABLE(cert) WITH SINGLE PARTITION, l): all separators of one or two vertices, or of more.

    The table's last two columns are u, v.
    """

    def __init__(self):
        self.edges, self.size = [], 1

    def eval(self, row, size):
        *_, u, v = row
        self.edges.append((u, v))
        self.size = size

    def terminate(self):
        from itertools import combinations

        g = graph_of(self.edges)
        whole = component_count(g)
        for chosen in combinations(sorted(g), self.size - 1):
            _, left = pieces_without_each_vertex(g, set(chosen))
            for v in sorted(left):
                if left[v] > whole and (not chosen or v > chosen[-1]):
                    yield self.size, [*chosen, v], left[v]


def _kappa(adjacency, u, v, cap):
    """Disjoint paths between u and v in a graph given as an array of (u, v) structs, up to cap."""
    g = graph_of([(e["u"], e["v"]) for e in adjacency], (u, v))
    return local_connectivity(g, u, v, cap)


def grouped_certificates(edges: DataFrame, graph: str, k: int) -> DataFrame:
    """Layered certificates of many small graphs at once: (graph, seq, u, v, layer), one task for each graph."""
    kind = edges.schema[graph].dataType.simpleString()

    def run(key, table):
        rows = layered_rows(list(zip(*(table[c].to_pylist() for c in ("seq", "u", "v")), strict=True)), k)
        cols = list(zip(*rows, strict=True)) if rows else [(), (), (), ()]
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int32())
        own = pa.array([key[0].as_py()] * len(rows), table.schema.field(graph).type)
        return pa.table([own, *(pa.array(c, t) for c, t in zip(cols, kinds, strict=True))], names=[graph, "seq", "u", "v", "layer"])

    return edges.groupBy(graph).applyInArrow(run, f"{graph} {kind}, seq long, u long, v long, layer int")


def grouped_verdicts(edges: DataFrame, graph: str, k: int) -> DataFrame:
    """(graph, n, verdict) for many small graphs at once."""
    kind = edges.schema[graph].dataType.simpleString()

    def run(key, table):
        g = graph_of(zip(table["u"].to_pylist(), table["v"].to_pylist(), strict=True))
        return pa.table([pa.array([key[0].as_py()], table.schema.field(graph).type), pa.array([len(g)], pa.int64()), pa.array([is_k_connected(g, k)])], names=[graph, "n", "verdict"])

    return edges.groupBy(graph).applyInArrow(run, f"{graph} {kind}, n long, verdict boolean")


def grouped_connectivity(edges: DataFrame, graph: str, k_max: int) -> DataFrame:
    """(graph, kappa): for many small graphs at once the largest k up to k_max, each from its online certificate."""
    kind = edges.schema[graph].dataType.simpleString()

    def run(key, table):
        cert = OnlineCertificate(k_max)
        for e in sorted(zip(*(table[c].to_pylist() for c in ("seq", "u", "v")), strict=True)):
            cert.offer(e)
        g = graph_of(((u, v) for _, u, v in cert.kept), {x for c in ("u", "v") for x in table[c].to_pylist()})
        low, high = 0, k_max
        while low < high:
            mid = (low + high + 1) // 2
            low, high = (mid, high) if is_k_connected(g, mid) else (low, mid - 1)
        return pa.table([pa.array([key[0].as_py()], table.schema.field(graph).type), pa.array([low], pa.int32())], names=[graph, "kappa"])

    return edges.groupBy(graph).applyInArrow(run, f"{graph} {kind}, kappa int")


def register_all(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Registers the functions, the generated-graph source and, where tables are given, a view for each workload."""
    from certgraph.sources.edge_files import KnownGraphSource
    from certgraph.sources.workloads import WORKLOADS

    spark.udtf.register("certificate_edges", F.udtf(CertificateEdges, returnType="seq long, u long, v long, layer int"))
    spark.udtf.register("k_separators", F.udtf(SmallSeparators, returnType="l int, members array<long>, pieces int"))
    spark.udf.register("kappa_capped", _kappa, "int")
    spark.dataSource.register(KnownGraphSource)
    if sf_dir:
        for name, make in WORKLOADS.items():
            make(spark, sf_dir).createOrReplaceTempView(f"graph_{name}")
