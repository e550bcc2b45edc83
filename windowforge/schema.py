"""Declared schemas of the stages, and the check on entry."""

from __future__ import annotations

from pyspark.sql import DataFrame

Schema = dict[str, str]


def declared(ddl: str) -> Schema:
    """Names and types as Spark prints them."""
    return {name: {"long": "bigint", "array<long>": "array<bigint>"}.get(kind, kind) for name, kind in (x.split() for x in ddl.split(", "))}


SEGMENTS = declared("seg_id string, doc_id long, seg_no int, n_tokens int")
VECTORS = declared("seg_id string, vec array<float>")
CENTROIDS = declared("cluster_id string, vec array<double>, n long")
MEMBERSHIP = declared("seg_id string, cluster_id string, cos double")
PACKED = declared("cluster_id string, seg_id string, doc_id long, seg_no int, n_tokens int, vec array<float>")
MANIFEST = declared("window_id string, pos int, seg_id string, start int, offset int, n_tokens int, used int, cut int")
EDGES = declared("src string, dst string, w double")
PATHS = declared("path_id long, pos long, seg_id string, exact boolean")


def require(df: DataFrame, schema: Schema, what: str = "input") -> DataFrame:
    """The columns of a schema in its order; says which is missing or of another type."""
    have = {f.name: f.dataType.simpleString() for f in df.schema}
    for name, kind in schema.items():
        if name not in have:
            raise ValueError(f"{what} has no column {name}; it has {', '.join(have)}")
        if have[name] != kind:
            raise ValueError(f"{what}: {name} is {have[name]}, not {kind}")
    return df.select(*schema)
