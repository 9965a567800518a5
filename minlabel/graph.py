"""Graphs as tables, and builders that make them from relational data."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from minlabel import schemas
from minlabel.operators import kernels
from minlabel.session import checkpoint, stored

#: A vertex with more edges than this, and than a quarter of a partition's share, is a hub: its edges lie in several parts.
HUB_ROWS = 1_000_000


def canonical_edges(df: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """Each undirected edge once, smaller end first, without loops."""
    a, b = F.col(src).cast("bigint"), F.col(dst).cast("bigint")
    return df.select(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst")).where("src < dst").distinct()


def directed_view(edges: DataFrame) -> DataFrame:
    """Both orientations of each edge, from one scan."""
    both = F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return edges.select(F.explode(both).alias("e")).select("e.src", "e.dst")


@dataclass
class Graph:
    """edges(src, dst) canonical, and vertices(id) with the isolated ones."""

    edges: DataFrame
    vertices: DataFrame
    name: str = ""
    names: DataFrame | None = field(default=None, repr=False)  # id, shown: where vertices are shown by other numbers than their ids
    raw: DataFrame | None = field(default=None, repr=False)  # the edges as given, with loops and repetitions but without nulls
    given: DataFrame | None = field(default=None, repr=False)  # the vertices that were given beside the edges
    _stored: DataFrame | None = field(default=None, repr=False)
    _directed: tuple[int, DataFrame] | None = field(default=None, repr=False)
    _source: tuple[DataFrame, DataFrame | None] | None = field(default=None, repr=False)  # edges, nulls too, and vertices that it was made from
    rows: int | None = field(default=None, repr=False)  # of raw, where it is known

    @classmethod
    def from_edges(cls, edges: DataFrame, vertices: DataFrame | None = None, name: str = "", check: bool = False) -> Graph:
        for c in ("src", "dst"):
            if not isinstance(edges.schema[c].dataType, schemas.INTEGERS):
                raise TypeError(f"{c} must be an integer; encode other keys with ids.encode_ids")
        if check and not edges.where("src is null or dst is null").isEmpty():
            raise ValueError("an edge has a null end")
        own = canonical_edges(edges)
        ends = edges.select(F.explode(F.array(F.col("src").cast("bigint"), F.col("dst").cast("bigint"))).alias("id")).where("id is not null")
        if vertices is not None:
            ends = ends.unionByName(vertices.select(F.col("id").cast("bigint").alias("id")).where("id is not null"))
        raw = edges.select(F.col("src").cast("bigint").alias("src"), F.col("dst").cast("bigint").alias("dst"))
        one_end = raw.where("src is null or dst is null").select(F.coalesce("src", "dst").alias("id")).where("id is not null")  # such a row has no edge, but a vertex
        given = one_end if vertices is None else one_end.unionByName(vertices.select(F.col("id").cast("bigint").alias("id")).where("id is not null"))
        return cls(own, ends.distinct(), name, raw=raw.dropna(), given=given, _source=(raw, vertices))

    def own_edges(self) -> DataFrame:
        """The canonical edges, made once for the whole run."""
        if self._stored is None:
            self._stored = stored(self.edges, "edges")
        return self._stored

    def kept(self) -> Graph:
        """The same graph with its edges as given, but for loops, and all its vertices, written once, for many runs over it."""
        if self._source is None:
            edges, vertices = self.own_edges(), self.vertices
            raw = edges if self.raw is None else stored(self.raw, "raw")
        else:
            out = Graph.from_edges(stored(self._source[0], "raw"), self._source[1])
            edges, vertices, raw = out.edges, out.vertices, out.raw
        raw = raw.where("src <> dst")
        return Graph(edges, stored(vertices, "vertices"), self.name, self.names, raw, rows=raw.count())

    def prepared(self, partitions: int, hub_rows: int = HUB_ROWS) -> DataFrame:
        """The directed view, dealt by src once for the whole run; rounds join it (joined_to) without moving it again. A hub's edges are dealt by src and salt: there are at most 4 hubs, and 8 parts of hubs, for each partition."""
        if self._directed is None or self._directed[0] != partitions:
            own = self.own_edges()
            directed, most = directed_view(own), max(hub_rows, -(-own.count() // (2 * partitions)))
            degrees = directed.groupBy("src").agg(F.count("*").alias("n")).where(F.col("n") > most)
            hubs = stored(degrees.select("src", F.ceil(F.col("n") / most).cast("int").alias("salts")), "hubs")
            if hubs.isEmpty():
                hubs = None
            else:
                directed = directed.join(F.broadcast(hubs), "src", "left").select("src", "dst", F.coalesce(F.pmod(F.xxhash64("dst"), F.col("salts")), F.lit(0)).cast("int").alias("salt"))
            self._directed = partitions, dealt(directed, partitions, hubs)
        return self._directed[1]


def dealt(directed: DataFrame, partitions: int, hubs: DataFrame | None) -> DataFrame:
    """Directed edges checkpointed by src, those of hubs (src, salts) by their salt too."""
    out = checkpoint(directed.repartition(partitions, "src") if hubs is None else directed.repartition(partitions, "src", "salt"))
    out._hubs = hubs
    return out


def hubs_of(directed: DataFrame) -> DataFrame | None:
    return getattr(directed, "_hubs", None)


def joined_to(directed: DataFrame, values: DataFrame) -> DataFrame:
    """Edges with the values(src, ...) of their src. The edges stay where they are; a hub's value is sent to each of its parts."""
    if (hubs := hubs_of(directed)) is None:
        return directed.join(values, "src")
    parts = F.explode(F.sequence(F.lit(0), F.coalesce("salts", F.lit(1)) - 1))
    sent = values.join(F.broadcast(hubs), "src", "left").withColumn("salt", parts).drop("salts")
    return directed.join(sent, ["src", "salt"])


def tagged(key: str | Column, tag: int, kinds: int = 2) -> Column:
    return (F.col(key) if isinstance(key, str) else key).cast("bigint") * kinds + tag


def bipartite_graph(df: DataFrame, left: str | Column, right: str | Column, isolated: DataFrame | None = None, name: str = "") -> Graph:
    edges = df.select(tagged(left, 0).alias("src"), tagged(right, 1).alias("dst")).dropna()
    return Graph.from_edges(edges, isolated, name)


def chain_graph(df: DataFrame, id: str, order: list[str], by: str | None = None, gap: Column | None = None, isolated: bool = True, name: str = "") -> Graph:
    """Each row with the next in order (within by, ties by id); gap: a condition on id, order and by of the row and its next_ columns that must hold. Rows are sorted by ranges over all of them, so no task holds a whole group, however large; rows that agree in all of these columns are one. Each meets the next where it lies, the last of a range the first of the next range in a table of two rows for each."""
    cols = list(dict.fromkeys([*([by] if by else []), *order, id]))
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    lain = df.select(*cols).distinct().repartitionByRange(n, *cols).sortWithinPartitions(*cols).withColumn("_range", F.spark_partition_id())
    own, after = [lain.schema[c] for c in cols], [StructField(f"next_{c}", lain.schema[c].dataType) for c in cols]
    schema = StructType([StructField(f.name, f.dataType) for f in own] + after + [StructField("_range", IntegerType()), StructField("_end", IntegerType())])
    met = stored(lain.mapInArrow(kernels.followers_kernel(len(cols)), schema), "followers")
    at = Window.orderBy("_range", "_end")
    ends = met.where("_end is not null").select(*cols, *[F.lead(c).over(at).alias(f"next_{c}") for c in cols], "_range", "_end").where("_end = 1")
    out = met.where("_end is null").unionByName(ends).where(F.col(f"next_{id}").isNotNull())
    out = out.where(F.col(by).eqNullSafe(F.col(f"next_{by}"))) if by else out
    out = out.where(gap) if gap is not None else out
    return Graph.from_edges(out.select(F.col(id).alias("src"), F.col(f"next_{id}").alias("dst")), df.select(F.col(id).alias("id")) if isolated else None, name)


def equality_graph(df: DataFrame, id: str, key: str | Column, name: str = "") -> Graph:
    """Rows of one key linked to the smallest of them: no pairs within a group. The smallest comes from a combined aggregate, so a hot key meets in no task."""
    keyed = df.select(F.col(id).cast("bigint").alias("dst"), (F.col(key) if isinstance(key, str) else key).alias("k"))
    first = keyed.groupBy("k").agg(F.min("dst").alias("src"), F.count("*").alias("n")).where("n > 1")
    return Graph.from_edges(keyed.join(first, "k").where("src <> dst").select("src", "dst"), df.select(F.col(id).alias("id")), name)


def similarity_graph(df: DataFrame, id: str, vector: str, threshold: float, blocks: int = 8, name: str = "") -> Graph:
    """Pairs of vectors whose cosine is over the threshold: all blocks of rows against all blocks, exact. Each pair of blocks is one group, of at most some 8,000 rows; a row is sent to as many groups as there are blocks. raw has of each group's pairs only as many as connect what they connect."""
    given = df.select(F.col(id).cast("bigint").alias("id")).where("id is not null")
    whole = df.select(F.col(id).cast("bigint").alias("id"), F.col(vector).cast("array<double>").alias("v")).where("id is not null and v is not null and not exists(v, x -> x is null)")
    blocks = max(blocks, -(-whole.count() // 4096))
    own = whole.withColumn("b", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    groups = own.select(F.least("b", "other").alias("i"), F.greatest("b", "other").alias("j"), "b", "id", "v").groupBy("i", "j")
    pairs, thin = (groups.applyInArrow(kernels.similar_pairs(threshold, t), "src bigint, dst bigint") for t in (False, True))
    return Graph(canonical_edges(pairs), given.distinct(), name, raw=thin, given=given)


def fk_graph(parts: list[DataFrame], name: str = "") -> Graph:
    """Tables of (src, dst) that are already tagged."""
    edges = parts[0]
    for p in parts[1:]:
        edges = edges.unionByName(p)
    return Graph.from_edges(edges, None, name)


def subgraph(g: Graph, vertex_pred: Column | None = None, edge_pred: Column | None = None) -> Graph:
    vertices = g.vertices if vertex_pred is None else g.vertices.where(vertex_pred)
    edges = g.edges if edge_pred is None else g.edges.where(edge_pred)
    if vertex_pred is not None:
        edges = edges.join(vertices.withColumnRenamed("id", "src"), "src", "left_semi").join(vertices.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst")
    return Graph(edges, vertices, g.name)
