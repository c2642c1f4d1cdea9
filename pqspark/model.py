"""Product-quantization models: configuration, codebooks and their stored forms."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class PQConfig:
    """chunks pieces of a dim-vector, 2**bits centroids (or k) in each.

    split: even (dim must divide), ragged (first pieces one longer) or pad (zeros behind).
    """

    dim: int = 64
    width: int = 16
    k: int = 256
    split: str = "even"
    iterations: int = 10
    seed: int = 42
    init: str = "hash"
    tol: float = 0.0
    empty: str = "keep"
    sample: int | None = None

    @property
    def chunks(self) -> int:
        if self.split == "even" and self.dim % self.width:
            raise ValueError(f"{self.dim} dimensions don't divide into pieces of {self.width}; use split='ragged' or 'pad'")
        return -(-self.dim // self.width) if self.split != "ragged" else max(1, self.dim // self.width)

    @property
    def bits(self) -> int:
        return max(1, (self.k - 1).bit_length())

    def offsets(self) -> list[int]:
        """First dimension of each piece, and the (padded) total."""
        m = self.chunks
        if self.split == "ragged":
            base, more = divmod(self.dim, m)
            return [j * base + min(j, more) for j in range(m + 1)]
        return [j * self.width for j in range(m + 1)]


@dataclass
class PQModel:
    """Codebooks on the driver: one [k, width] table per chunk; a model is a few MB whatever the data holds."""

    config: PQConfig
    books: list[np.ndarray]
    inertia: list[float] = field(default_factory=list)
    model_id: str = "pq"

    def __post_init__(self) -> None:
        self.bias = [0.5 * (b * b).sum(axis=1) for b in self.books]
        self.lanes = [np.ascontiguousarray(b.T) for b in self.books]
        self.offsets = self.config.offsets()
        self.tables: dict = {}  # forms of the codebooks that kernels make once
        self.spread = max((float(np.abs(b).max(initial=0.0)) for b in self.books), default=0.0)

    def __getstate__(self) -> dict:
        return self.__dict__ | {"tables": {}}

    @property
    def k(self) -> int:
        return len(self.books[0])

    @property
    def chunks(self) -> int:
        return len(self.books)

    @property
    def code_type(self) -> str:
        return "smallint" if self.k <= 1 << 15 else "int"

    def codebook(self, spark: SparkSession) -> DataFrame:
        """(chunk, centroid, coords, bias): m * k rows."""
        rows = [(j, c, b[c].tolist(), float(self.bias[j][c])) for j, b in enumerate(self.books) for c in range(len(b))]
        return spark.createDataFrame(rows, "chunk int, centroid int, coords array<double>, bias double")

    def save(self, spark: SparkSession, path: str) -> None:
        self.codebook(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/codebook")
        meta = [(self.model_id, json.dumps(asdict(self.config)), [float(x) for x in self.inertia])]
        spark.createDataFrame(meta, "model_id string, config string, inertia array<double>").coalesce(1).write.mode("overwrite").parquet(f"{path}/meta")

    @staticmethod
    def load(spark: SparkSession, path: str) -> PQModel:
        meta = spark.read.parquet(f"{path}/meta").first()
        config = PQConfig(**json.loads(meta.config))
        return PQModel.from_rows(config, spark.read.parquet(f"{path}/codebook"), list(meta.inertia), meta.model_id)

    @staticmethod
    def from_rows(config: PQConfig, codebook: DataFrame, inertia: list[float] | None = None, model_id: str = "pq") -> PQModel:
        books: dict[int, list] = {}
        for r in codebook.orderBy("chunk", "centroid").select("chunk", "coords").collect():
            books.setdefault(r.chunk, []).append(r.coords)
        return PQModel(config, [np.array(books[j]) for j in sorted(books)], inertia or [], model_id)

    def diff(self, other: PQModel) -> float:
        """The largest difference of a coordinate."""
        return max(float(np.abs(a - b).max()) for a, b in zip(self.books, other.books, strict=True))
