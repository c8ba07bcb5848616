"""Sample contract: every table binds to (sample_id, payload, stratum)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BYTES, VECTOR, BANDS = "bytes", "vector", "bands"


@dataclass(frozen=True)
class SampleSpec:
    """table and its id and payload columns; kind says how the payload becomes levels. id may be an SQL expression."""

    table: str
    id_col: str
    payload_col: str
    kind: str
    stratum_col: str | None = None

    def bind(self, df: DataFrame) -> DataFrame:
        stratum = F.expr(self.stratum_col).cast("string") if self.stratum_col else F.lit(None).cast("string")
        return df.select(F.expr(self.id_col).cast("long").alias("sample_id"), F.expr(self.payload_col).alias("payload"), stratum.alias("stratum"))


DOCUMENTS = SampleSpec("documents", "doc_id", "text", BYTES, "lang")
PAGES = SampleSpec("pages", "page_id", "html", BYTES)
CONVERSATIONS = SampleSpec("conversations", "conv_id * 1000 + turn", "text", BYTES, "role")
EMBEDDINGS = SampleSpec("embeddings", "vec_id", "embedding", VECTOR, "label")


def check_contract(df: DataFrame, unique: bool = False) -> None:
    """Raise where the contract is broken: columns, id type, null ids, and on demand repeated ids."""
    kinds = dict(df.dtypes)
    missing = {"sample_id", "payload"} - kinds.keys()
    if missing:
        raise ValueError(f"missing columns: {sorted(missing)}")
    if kinds["sample_id"] != "bigint":
        raise ValueError(f"sample_id must be bigint, not {kinds['sample_id']}")
    if not df.filter("sample_id IS NULL").isEmpty():
        raise ValueError("null sample_id")
    if unique and not df.groupBy("sample_id").count().filter("count > 1").isEmpty():
        raise ValueError("repeated sample_id")
