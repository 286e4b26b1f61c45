"""Schemas of index tables, logs, hits and traces. Never inferred."""

from __future__ import annotations

import pyarrow as pa

POINTS = "label long, vec array<float>, version long"
QUERIES = "query_id long, vec array<float>"
LOG = "seq long, op string, label long, vec array<float>"
#: One row per slot: its node record and its out-list in each layer; the entry point's row also holds counters.
INDEX = "role string, shard int, slot long, label long, vec array<float>, version long, level int, deleted_seq long, entry boolean, nbrs array<array<long>>, stats map<string,double>"
HITS = "query_id long, rank int, label long, version long, dist double, source string"
TRACE = "scenario string, dataset string, strategy string, iter int, metric string, value double"


def arrow_type(ddl: str) -> pa.DataType:
    ddl = ddl.strip()
    plain = {"long": pa.int64(), "int": pa.int32(), "string": pa.string(), "double": pa.float64(), "float": pa.float32(), "boolean": pa.bool_()}
    if ddl in plain:
        return plain[ddl]
    inner = ddl[ddl.index("<") + 1 : -1]
    if ddl.startswith("array<"):
        return pa.list_(arrow_type(inner))
    key, _, value = inner.partition(",")
    return pa.map_(arrow_type(key), arrow_type(value))


def arrow_schema(ddl: str) -> pa.Schema:
    """Arrow's schema of the column lists above; works in tasks, where there is no Spark session."""
    return pa.schema([(c.split()[0], arrow_type(c.split(None, 1)[1])) for c in ddl.split(", ")])
