"""A small network as data: analytic weights for exact checks, NumPy parameters, a model store."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bloommap import BloomMap
from .features import FeatureGroup, Template


@dataclass(frozen=True)
class AnalyticModel:
    """Weights by an integer formula, so that every engine computes the same numbers.

    Embeddings are eighths, the hidden layer and the output are whole numbers; the averaged
    input is cut to 1/1024. All sums are exact in 64-bit integers.
    """

    orders: tuple[int, ...] = (1, 2, 3, 4)
    vocab: tuple[int, ...] = (100, 500, 1000, 5000)
    dim: int = 4
    hidden: int = 8
    classes: tuple[str, ...] = ("de", "en", "es", "fr")

    @property
    def h0(self) -> int:
        return self.dim * len(self.orders)

    def embedding(self, g, v, d):
        return (v * (31 + 7 * d) + 17 * g + 5 * d * d) % 15 - 7

    def hidden_weight(self, j: int, i: int) -> int:
        return (7 * i + 13 * j + i * j) % 9 - 4

    def hidden_bias(self, j: int) -> int:
        return (j % 5) * 64

    def output_weight(self, y: int, j: int) -> int:
        return (11 * y + 5 * j + y * j) % 7 - 3

    def embedding_table(self, spark: SparkSession) -> DataFrame:
        """(grp, v, w): at most the sum of the vocabulary sizes."""
        parts = [spark.range(size).select(F.lit(g).alias("grp"), F.col("id").cast("int").alias("v"), F.array(*[self.embedding(g, F.col("id"), d).cast("int") for d in range(self.dim)]).alias("w")) for g, size in enumerate(self.vocab)]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out


@dataclass
class Network:
    """Trained parameters: one embedding matrix per group, hidden layer, output."""

    template: Template
    classes: list[str]
    embeddings: list[np.ndarray]
    w: np.ndarray
    c: np.ndarray
    beta: np.ndarray
    b: np.ndarray
    resources: dict = field(default_factory=dict)

    @staticmethod
    def random(template: Template, hidden: int, classes: list[str], seed: int = 1, scale: float = 0.1) -> Network:
        rng = np.random.default_rng(seed)
        emb = [rng.normal(0, scale, (g.vocab, g.dim)).astype(np.float32) for g in template.groups]
        w = rng.normal(0, np.sqrt(2 / template.h0), (hidden, template.h0)).astype(np.float32)
        beta = rng.normal(0, np.sqrt(1 / hidden), (len(classes), hidden)).astype(np.float32)
        return Network(template, list(classes), emb, w, np.full(hidden, 0.1, np.float32), beta, np.zeros(len(classes), np.float32))

    def parameters(self) -> list[np.ndarray]:
        return [*self.embeddings, self.w, self.c, self.beta, self.b]

    def copy(self) -> Network:
        return Network(self.template, self.classes, [e.copy() for e in self.embeddings], self.w.copy(), self.c.copy(), self.beta.copy(), self.b.copy(), dict(self.resources))

    def rows(self, group: int, ids: np.ndarray) -> np.ndarray:
        """Embeddings of the ids of one group."""
        return self.embeddings[group][ids]

    def product(self, group: int, counts: np.ndarray) -> np.ndarray:
        """Sums of embeddings, for rows of counts over the whole vocabulary of a group."""
        return counts @ self.embeddings[group]

    def logits(self, h0: np.ndarray) -> np.ndarray:
        return np.maximum(h0 @ self.w.T + self.c, 0) @ self.beta.T + self.b


def save(spark: SparkSession, net: Network, path: str) -> None:
    """A folder: parameters as one Parquet table, the specification as JSON, and the cluster map if there is one."""
    names = [f"embedding{i}" for i in range(len(net.embeddings))] + ["w", "c", "beta", "b"]
    rows = [(n, list(map(int, p.shape)), p.astype(np.float32).ravel().tolist()) for n, p in zip(names, net.parameters(), strict=True)]
    spark.createDataFrame(rows, "name string, shape array<int>, value array<float>").coalesce(1).write.mode("overwrite").parquet(f"{path}/parameters")
    spec = json.dumps({"groups": [asdict(g) for g in net.template.groups], "classes": net.classes, "resources": {k: v for k, v in net.resources.items() if isinstance(v, str | int | float | list | dict)}})
    spark.createDataFrame([(spec,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/spec")
    held = net.resources.get("clusters")
    about = [] if held is None else [(bytearray(held.bits.tobytes()), json.dumps({"size": held.size, "hashes": list(held.hashes.items()), "values": held.values, "codes": list(held.codes.items()), "variant": held.variant}))]
    spark.createDataFrame(about, "bits binary, about string").coalesce(1).write.mode("overwrite").parquet(f"{path}/map")


def load(spark: SparkSession, path: str) -> Network:
    spec = json.loads(spark.read.text(f"{path}/spec").first()["value"])
    got = {r["name"]: np.array(r["value"], np.float32).reshape(r["shape"]) for r in spark.read.parquet(f"{path}/parameters").collect()}
    template = Template(tuple(FeatureGroup(**g) for g in spec["groups"]))
    for r in spark.read.parquet(f"{path}/map").collect():
        about = json.loads(r["about"])
        spec["resources"]["clusters"] = BloomMap(np.frombuffer(bytes(r["bits"]), np.uint64), about["size"], dict(about["hashes"]), about["values"], dict(about["codes"]), about["variant"])
    return Network(template, spec["classes"], [got[f"embedding{i}"] for i in range(len(template.groups))], got["w"], got["c"], got["beta"], got["b"], spec["resources"])
