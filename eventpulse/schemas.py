"""Declared schemas."""

from __future__ import annotations

import pyarrow as pa

POST = "post_id long, ts timestamp, region string, text string"
CLUSTER = "region string, block_no long, shard int, cluster_id string, n_posts long, min_post long, vec map<string,double>, cosines long"
FOLD = (
    "kind string, region string, block_no long, cluster_id string, n_added long, n_posts long, growth double, "
    "born_block long, last_block long, is_event boolean, vec map<string,double>, metric string, value double"
)
COST = "run_id string, variant string, block_no long, metric string, value double"

_ARROW = {"string": pa.string(), "long": pa.int64(), "int": pa.int32(), "double": pa.float64(), "boolean": pa.bool_(), "map<string,double>": pa.map_(pa.string(), pa.float64())}


def arrow_rows(rows: list[tuple], schema: str) -> pa.RecordBatch:
    """Rows as a batch of one of the schemas above; maps are given as dicts."""
    fields = [f.split() for f in schema.split(", ")]
    cols = list(zip(*rows, strict=True)) or [() for _ in fields]
    plain = lambda c, t: [None if v is None else list(v.items()) for v in c] if t.startswith("map") else c
    return pa.RecordBatch.from_arrays([pa.array(plain(c, t), _ARROW[t]) for c, (_, t) in zip(cols, fields, strict=True)], [n for n, _ in fields])
