"""The index: partitions, their models, packed rows, attribute cells (M22), built in one pass of training and one of encoding."""

from __future__ import annotations

import hashlib
import json
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from packvec.operators import attributes as at
from packvec.operators import lowbit, partitioner, rotate, segments, select
from packvec.operators.quantizers import lloyd_edges
from packvec.plans.shared import stored


@dataclass(frozen=True)
class Config:
    """bits: of a dimension on average. quantizer: lloyd, uniform or equal_depth. rotation: partition, global or none.

    allocation: variance or uniform. lowbit_space: rotated or raw. Groups of over chunk_rows rows are handled in chunks.
    """

    partitions: int = 4
    bits: int = 4
    seg_bits: int = 8
    decay: float = 4.0
    max_bits: int = 12
    quantizer: str = "lloyd"
    rotation: str = "partition"
    allocation: str = "variance"
    lowbit_space: str = "rotated"
    balanced: bool = True
    slack: float = 0.05
    beta: float = 0.001
    attr_bits: int = 5
    rounds: int = 15
    train_rows: int = 1_000_000
    chunk_rows: int = 200_000
    by_column: str | None = None


MODEL = "part_id int, n long, mean array<double>, rotation array<double>, bits array<int>, edges array<array<double>>, low_mean array<double>"


def allocate_bits(variance: np.ndarray, budget: int, decay: float, most: int) -> np.ndarray:
    """Array twin of operators.bits.allocate."""
    t = np.arange(most)
    worth = variance[:, None] / decay ** t[None, :]
    dim, step = np.divmod(np.arange(worth.size), most)
    order = np.lexsort((step, dim, -worth.ravel()))[:budget]
    return np.bincount(dim[order], minlength=len(variance))


def train(x: np.ndarray, cfg: Config, rotation: np.ndarray | None = None, whole: bool = True) -> dict:
    """The model of one partition from its vectors; whole says that they are all of them."""
    n, d = x.shape
    mean = x.mean(0) if n else np.zeros(d)
    if cfg.rotation == "none":
        turn = np.eye(d)
    elif rotation is not None:
        turn = rotation
    else:
        _, turn = rotate.basis(n, x.sum(0), x.T @ x)
    y = (x - mean) @ turn
    budget = cfg.bits * d
    if cfg.allocation == "variance":
        bits = allocate_bits(np.round(y.var(0), 12), budget, cfg.decay, cfg.max_bits)
    else:
        bits = np.full(d, cfg.bits)
    edges = []
    for j in range(d):
        v, cells = y[:, j], 1 << int(bits[j])
        if cfg.quantizer == "lloyd":
            e = lloyd_edges(v, cells, cfg.rounds)
        elif cfg.quantizer == "uniform":
            e = np.linspace(v.min(), v.max(), cells + 1)
        else:
            e = np.unique(np.quantile(v, np.linspace(0, 1, cells + 1)))
            e = e if len(e) > 1 else np.repeat(e, 2)
        if not whole:
            e = np.r_[-np.inf, e[1:-1], np.inf]
        edges.append(e)
    return {"mean": mean, "rotation": turn, "bits": bits, "edges": edges, "low_mean": np.zeros(d) if cfg.lowbit_space == "rotated" else mean}


def encode_rows(y: np.ndarray, edges: list[np.ndarray]) -> np.ndarray:
    out = np.zeros(y.shape, np.int64)
    for j, e in enumerate(edges):
        out[:, j] = np.clip(np.searchsorted(e, y[:, j], "right") - 1, 0, len(e) - 2)
    return out


@dataclass
class Index:
    """models: one row a partition. rows: part_id, chunk, vec_id, packed, low, attribute cells and numbers. vectors: part_id, vec_id, embedding."""

    cfg: Config
    d: int
    models: DataFrame
    rows: DataFrame
    vectors: DataFrame
    centroids: DataFrame
    attributes: dict[str, at.Attribute] = field(default_factory=dict)
    threshold: float = 1.0

    def manifest(self) -> DataFrame:
        """One row: a fingerprint of settings and counts."""
        n = self.rows.groupBy("part_id").agg(F.count(F.lit(1)).alias("n"))
        total = n.agg(F.sum("n").alias("n_rows"), F.count(F.lit(1)).alias("n_partitions"), F.max("n").alias("largest"), F.min("n").alias("smallest"))
        settings = json.dumps({**asdict(self.cfg), "d": self.d}, sort_keys=True)
        return total.select(F.lit(hashlib.sha256(settings.encode()).hexdigest()[:16]).alias("settings"), F.lit(self.d).alias("d"), "n_rows", "n_partitions", "largest", "smallest", F.lit(self.threshold).alias("threshold"))

    def save(self, path: str) -> None:
        for name in ("models", "rows", "vectors", "centroids"):
            df = getattr(self, name)
            (df.write.mode("overwrite").partitionBy("part_id") if name in ("rows", "vectors") else df.write.mode("overwrite")).parquet(f"{path}/{name}")
        facts = {"cfg": asdict(self.cfg), "d": self.d, "threshold": self.threshold, "attributes": {k: asdict(a) for k, a in self.attributes.items()}}
        self.models.sparkSession.createDataFrame([(json.dumps(facts),)], "facts string").write.mode("overwrite").json(f"{path}/facts")


def load(spark: SparkSession, path: str) -> Index:
    facts = json.loads(spark.read.schema("facts string").json(f"{path}/facts").first()["facts"])
    read = lambda n: spark.read.parquet(f"{path}/{n}")
    return Index(Config(**facts["cfg"]), facts["d"], read("models"), read("rows"), read("vectors"), read("centroids"), {k: at.Attribute(**a) for k, a in facts["attributes"].items()}, facts["threshold"])


def homes(df: DataFrame, cfg: Config) -> tuple[DataFrame, DataFrame]:
    """(vec_id, part_id) and (part_id, centroid)."""
    spark = df.sparkSession
    if cfg.by_column:
        own = partitioner.by_column(df, cfg.by_column)
        labelled = df.select("embedding", F.col(cfg.by_column).cast("int").alias("label"))
        from packvec.sources.tables import label_centroids

        return own, label_centroids(labelled)
    if cfg.partitions == 1:
        means = df.select(F.posexplode("embedding").alias("dim", "x")).groupBy("dim").agg(F.avg("x").alias("m"))
        one = means.agg(F.transform(F.array_sort(F.collect_list(F.struct("dim", "m"))), lambda s: s["m"]).alias("centroid")).select(F.lit(0).alias("part_id"), "centroid")
        return df.select("vec_id", F.lit(0).alias("part_id")), one
    own, centroids = partitioner.kmeans(df, cfg.partitions, balanced=cfg.balanced, slack=cfg.slack)
    return own, spark.createDataFrame([(i, [float(v) for v in c]) for i, c in enumerate(centroids)], "part_id int, centroid array<double>")


def encoder(cfg: Config, d: int, extra: list[str]):
    """Rows of one chunk and their partition's model into packed rows."""

    def run(rows: pa.Table, model: pa.Table) -> pa.Table:
        if rows.num_rows == 0 or model.num_rows == 0:
            return _no_rows(rows, extra)
        m = {c: model.column(c)[0].as_py() for c in ("mean", "rotation", "bits", "edges", "low_mean")}
        x = np.asarray(rows.column("embedding").combine_chunks().flatten(), float).reshape(-1, d)
        y = (x - np.array(m["mean"])) @ np.array(m["rotation"]).reshape(d, d)
        codes = encode_rows(y, [np.array(e) for e in m["edges"]])
        packed = segments.pack_matrix(codes, m["bits"], cfg.seg_bits)
        low = lowbit.pack_signs((y if cfg.lowbit_space == "rotated" else x) - np.array(m["low_mean"]))
        return pa.table({**{c: rows.column(c) for c in ("part_id", "chunk", "vec_id")}, "packed": pa.array([r.tobytes() for r in packed], pa.binary()), "low": pa.array([r.tobytes() for r in low], pa.binary()), **{c: rows.column(c) for c in extra}})

    return run


def _no_rows(rows: pa.Table, extra: list[str]) -> pa.Table:
    empty = rows.slice(0, 0)
    return pa.table({**{c: empty.column(c) for c in ("part_id", "chunk", "vec_id")}, "packed": pa.array([], pa.binary()), "low": pa.array([], pa.binary()), **{c: empty.column(c) for c in extra}})


def build(df: DataFrame, attribute_names: list[str] | None = None, cfg: Config = Config()) -> Index:
    """An index of df (vec_id, embedding and attribute columns). Vectors must be valid (sources.tables.split_valid)."""
    first = df.select(F.size("embedding").alias("d")).first()
    d = first["d"] if first else 0
    kinds = at.describe(df, attribute_names or [], cfg.attr_bits)
    own, centroids = homes(df, cfg)
    coded = at.quantized(df, kinds)
    extra = [f"{p}{a}" for a in kinds for p in ("c_", "x_")]
    placed = coded.join(own, "vec_id").select(F.col("part_id").cast("int"), "vec_id", F.col("embedding").cast("array<double>").alias("embedding"), *extra)
    vectors = stored(placed, "vectors")
    sizes = vectors.groupBy("part_id").agg(F.count(F.lit(1)).alias("n"))
    chunks = sizes.withColumn("chunks", F.ceil(F.col("n") / cfg.chunk_rows).cast("int"))
    shared_turn = None
    if cfg.rotation == "global":
        m = rotate.fit(vectors.select("part_id", "embedding"), d, "global").first()
        shared_turn = np.array(m["rotation"]).reshape(d, d)
    share = F.least(F.lit(cfg.train_rows) / F.col("n"), F.lit(1.0))
    sample = vectors.select("part_id", "vec_id", "embedding").join(sizes, "part_id").where(F.pmod(F.xxhash64("vec_id"), F.lit(1_000_000)) < share * 1_000_000)

    def fit(t: pa.Table) -> pa.Table:
        x = np.asarray(t.column("embedding").combine_chunks().flatten(), float).reshape(-1, d)
        n = t.column("n")[0].as_py()
        m = train(x, cfg, shared_turn, len(x) == n)
        return pa.table({"part_id": t.column("part_id").slice(0, 1), "n": pa.array([n], pa.int64()), "mean": pa.array([m["mean"].tolist()], pa.list_(pa.float64())), "rotation": pa.array([m["rotation"].ravel().tolist()], pa.list_(pa.float64())), "bits": pa.array([m["bits"].tolist()], pa.list_(pa.int32())), "edges": pa.array([[e.tolist() for e in m["edges"]]], pa.list_(pa.list_(pa.float64()))), "low_mean": pa.array([m["low_mean"].tolist()], pa.list_(pa.float64()))})

    models = stored(sample.select("part_id", "embedding", "n").groupBy("part_id").applyInArrow(fit, MODEL), "models")
    chunked = vectors.join(chunks.select("part_id", "chunks"), "part_id").withColumn("chunk", F.pmod(F.xxhash64("vec_id"), F.col("chunks")).cast("int")).drop("chunks")
    per_chunk = models.join(chunks.select("part_id", "chunks"), "part_id").withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    types = {f.name: f.dataType.simpleString() for f in chunked.schema.fields}
    schema = "part_id int, chunk int, vec_id long, packed binary, low binary" + "".join(f", {c} {types[c]}" for c in extra)
    rows = stored(chunked.groupBy("part_id", "chunk").cogroup(per_chunk.groupBy("part_id", "chunk")).applyInArrow(encoder(cfg, d, extra), schema), "rows", "part_id")
    rows = rows.withColumn("part_id", F.col("part_id").cast("int"))
    index = Index(cfg, d, models, rows, vectors, stored(centroids.withColumn("part_id", F.col("part_id").cast("int")), "centroids"), kinds)
    some = vectors.orderBy(F.xxhash64("vec_id")).limit(10_000)
    index.threshold = select.centroid_factor(some, index.centroids, d, cfg.beta).first()["threshold"] or 1.0
    return index


def append(index: Index, df: DataFrame) -> Index:
    """The index with more rows (M22): nearest homes, old models, wider edges. Rows whose ids it has are replaced.

    Values beyond an attribute's or a dimension's outer edges widen them. Unknown categories need a new index.
    """
    d, cfg = index.d, index.cfg
    kinds = {}
    for a in index.attributes.values():
        if a.kind == "category":
            odd = df.where(F.col(a.name).isNotNull() & ~F.col(a.name).cast("string").isin(a.values))
            if not odd.isEmpty():
                raise ValueError(f"{a.name} has values that the index does not know")
            kinds[a.name] = a
        else:
            low, high = df.agg(F.min(at.number(df, a.name)), F.max(at.number(df, a.name))).first()
            edges = list(a.edges)
            edges[0], edges[-1] = min(edges[0], edges[0] if low is None else low), max(edges[-1], edges[-1] if high is None else high)
            kinds[a.name] = at.Attribute(a.name, a.kind, edges, a.values)
    known = index.centroids.orderBy("part_id").collect()  # an index artefact
    homes = partitioner._nearest(df, np.array([r["centroid"] for r in known]), 1)
    parts = F.array(*[F.lit(r["part_id"]) for r in known])
    own = homes.select("vec_id", F.get(parts, F.col("part_id")).alias("part_id"))
    extra = [f"{p}{a}" for a in kinds for p in ("c_", "x_")]
    placed = stored(at.quantized(df, kinds).join(own, "vec_id").select("part_id", "vec_id", F.col("embedding").cast("array<double>").alias("embedding"), *extra), "more")
    wide = lambda e: F.concat(F.array(F.lit(float("-inf"))), F.slice(e, 2, F.size(e) - 2), F.array(F.lit(float("inf"))))
    models = stored(index.models.withColumn("edges", F.transform("edges", wide)), "models")
    last = index.rows.groupBy("part_id").agg(F.max("chunk").alias("last"))
    sizes = placed.groupBy("part_id").agg(F.ceil(F.count(F.lit(1)) / cfg.chunk_rows).cast("int").alias("more")).join(last, "part_id", "left")
    sizes = stored(sizes.select("part_id", "more", (F.coalesce("last", F.lit(-1)) + 1).alias("first")), "sizes")
    chunked = placed.join(sizes, "part_id").withColumn("chunk", (F.col("first") + F.pmod(F.xxhash64("vec_id"), F.col("more"))).cast("int")).drop("more", "first")
    per_chunk = models.join(sizes.select((F.col("part_id") + 0).alias("part_id"), "more", "first"), "part_id").withColumn("chunk", F.explode(F.sequence(F.col("first"), F.col("first") + F.col("more") - 1))).drop("more", "first")
    types = {f.name: f.dataType.simpleString() for f in chunked.schema.fields}
    schema = "part_id int, chunk int, vec_id long, packed binary, low binary" + "".join(f", {c} {types[c]}" for c in extra)
    rows = chunked.groupBy("part_id", "chunk").cogroup(per_chunk.groupBy("part_id", "chunk")).applyInArrow(encoder(cfg, d, extra), schema)
    new = placed.select("vec_id")
    rows = stored(index.rows.join(new, "vec_id", "left_anti").unionByName(rows), "rows", "part_id").withColumn("part_id", F.col("part_id").cast("int"))
    vectors = stored(index.vectors.join(new, "vec_id", "left_anti").unionByName(placed), "vectors")
    return Index(cfg, d, models, rows, vectors, index.centroids, kinds, index.threshold)
