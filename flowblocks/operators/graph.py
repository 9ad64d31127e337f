"""Region graphs. A graph has at most MAX_REGIONS vertices (checked), so the driver holds its adjacency."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

MAX_REGIONS = 4096


class Graph:
    def __init__(self, n: int, pairs):
        if n > MAX_REGIONS:
            raise ValueError(f"{n} regions; the bound is {MAX_REGIONS}")
        self.n, self.adj = n, {v: set() for v in range(n)}
        for u, v in pairs:
            if u != v:
                self.adj[u].add(v)
                self.adj[v].add(u)

    def neighbours(self, v: int) -> list[int]:
        return sorted(self.adj[v])

    def is_connected(self, verts) -> bool:
        verts = set(verts)
        seen = todo = {min(verts)} if verts else set()
        while todo:
            todo = {w for v in todo for w in self.adj[v]} & verts - seen
            seen = seen | todo
        return bool(verts) and seen == verts

    def components(self) -> list[list[int]]:
        left, out = set(range(self.n)), []
        while left:
            seen = todo = {min(left)}
            while todo:
                todo = {w for v in todo for w in self.adj[v]} - seen
                seen = seen | todo
            out.append(sorted(seen))
            left -= seen
        return out

    def dfs_ids(self) -> dict[int, int]:
        """Depth-first numbers from the vertex of least degree, so near regions get near numbers."""
        key = lambda v: (len(self.adj[v]), v)
        out: dict[int, int] = {}
        for root in sorted(self.adj, key=key):
            stack = [root]
            while stack:
                if (v := stack.pop()) not in out:
                    out[v] = len(out)
                    stack += sorted(self.adj[v] - out.keys(), key=key, reverse=True)
        return out


def grid_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nations on a grid: column n_regionkey, row the rank within it."""
    n = spark.read.parquet(f"{sf_dir}/nation.parquet").select("n_nationkey", "n_regionkey", F.row_number().over(Window.partitionBy("n_regionkey").orderBy("n_nationkey")).alias("row"))
    a, b = n.toDF("u", "cu", "ru"), n.toDF("v", "cv", "rv")
    near = ((F.col("cu") == F.col("cv")) & (F.abs(F.col("ru") - F.col("rv")) == 1)) | ((F.col("ru") == F.col("rv")) & (F.abs(F.col("cu") - F.col("cv")) == 1))
    return a.join(b, near).select("u", "v")


def dense_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nations of the same or an adjacent region."""
    n = spark.read.parquet(f"{sf_dir}/nation.parquet").select("n_nationkey", "n_regionkey")
    a, b = n.toDF("u", "cu"), n.toDF("v", "cv")
    return a.join(b, (F.col("u") != F.col("v")) & (F.abs(F.col("cu") - F.col("cv")) <= 1)).select("u", "v")


def path_edges(regions: DataFrame) -> DataFrame:
    """Regions with adjacent numbers, of those that stand in the only column."""
    a = regions.toDF("u").where("u is not null").distinct()
    return a.join(a.toDF("v"), F.abs(F.col("u") - F.col("v")) == 1)


def checked(edges: DataFrame) -> list[tuple[int, int]]:
    """Distinct pairs on the driver; more than MAX_REGIONS x MAX_REGIONS of them is an error, never a cut."""
    rows = edges.select(F.col(edges.columns[0]).alias("u"), F.col(edges.columns[1]).alias("v")).where("u <> v").distinct().limit(MAX_REGIONS * MAX_REGIONS + 1)
    out = [(r[0], r[1]) for r in rows.toLocalIterator()]
    if len(out) > MAX_REGIONS * MAX_REGIONS:
        raise ValueError(f"more pairs than {MAX_REGIONS} regions can have")
    return out


def from_edges(edges: DataFrame, n: int) -> Graph:
    return Graph(n, checked(edges))


def path(n: int) -> Graph:
    return Graph(n, ((i, i + 1) for i in range(n - 1)))


def square(side: int) -> Graph:
    return Graph(side * side, [(i, i + 1) for i in range(side * side) if (i + 1) % side] + [(i, i + side) for i in range(side * (side - 1))])


def component_rows(spark: SparkSession, graph: Graph) -> DataFrame:
    """v, component (its smallest vertex) for every vertex."""
    return spark.createDataFrame([(v, c[0]) for c in graph.components() for v in c], "v int, component int")


def induced(edges: DataFrame, verts: list[int]) -> DataFrame:
    """The pairs of a graph between the given vertices."""
    return edges.where(F.col("u").isin(verts) & F.col("v").isin(verts))
