"""Schemas of the engine's tables, and a check on entry."""

from __future__ import annotations

from pyspark.sql import DataFrame

WORKERS = {"worker_id": "int", "family": "string", "cores": "int", "mem_gb": "int", "sec_per_batch": "double"}
TIMINGS = {"worker_id": "int", "iter": "bigint", "n_rows": "bigint", "batch_rows": "int", "epochs": "int", "t_train": "double"}
LOSSES = {"worker_id": "int", "iter": "bigint", "loss": "double"}
ALLOCATION = {"worker_id": "int", "n_rows": "bigint", "batch_rows": "int", "t_pred": "double"}
RUN_LOG = {"run_id": "string", "seq": "bigint", "vtime": "double", "worker_id": "int", "kind": "string", "bytes": "bigint", "global_version": "bigint"}
TRAJECTORY = {"run_id": "string", "global_version": "bigint", "vtime": "double", "worker_id": "int", "loss": "double", "accuracy": "double"}

INTEGRAL = ("tinyint", "smallint", "int", "bigint")


def ddl(schema: dict[str, str]) -> str:
    return ", ".join(f"{n} {t}" for n, t in schema.items())


def assert_schema(df: DataFrame, schema: dict[str, str]) -> DataFrame:
    """df, if it has the columns with these types (whole numbers of any width do)."""
    have = dict(df.dtypes)
    for name, kind in schema.items():
        if name not in have:
            raise ValueError(f"column {name} is missing; there are {sorted(have)}")
        if have[name] != kind and not (kind in INTEGRAL and have[name] in INTEGRAL):
            raise ValueError(f"column {name} is {have[name]}, not {kind}")
    return df
