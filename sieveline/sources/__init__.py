"""Readers of document collections and of pipeline files, and sinks."""

from __future__ import annotations

import json
from dataclasses import MISSING, fields, is_dataclass
from pathlib import Path
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def read_documents(spark: SparkSession, path: str, kind: str | None = None, schema: StructType | str | None = None) -> DataFrame:
    """A collection from Parquet, JSON lines, a JSON array, CSV, whole text files or binary files.

    Bad JSON rows come back in ``_corrupt_record`` when the schema names it.
    """
    kind = kind or path.rstrip("/").rpartition(".")[2]
    reader = spark.read.schema(schema) if schema is not None else spark.read
    if kind in ("parquet", "orc"):
        return reader.format(kind).load(path)
    if kind in ("json", "jsonl"):
        return reader.option("multiLine", kind == "json").option("mode", "PERMISSIVE").json(path)
    if kind == "csv":
        return reader.option("header", True).option("escape", '"').option("multiLine", True).csv(path)
    if kind == "text":
        return spark.read.option("wholetext", True).text(path).withColumn("path", F.input_file_name())
    if kind == "binary":
        return spark.read.format("binaryFile").load(path)
    raise ValueError(f"unknown kind of source: {kind}")


def write_documents(df: DataFrame, path: str, kind: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    df.write.mode(mode).partitionBy(*partition_by).format("json" if kind == "jsonl" else kind).save(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """Chunks stored by document, so that gather and reduce by document need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def _kinds() -> dict[str, type]:
    from ..plans import ir

    return {"map": ir.MapOp, "parallel_map": ir.ParallelMapOp, "filter": ir.FilterOp, "project": ir.ProjectOp, "unnest": ir.UnnestOp, "split": ir.SplitOp, "gather": ir.GatherOp, "reduce": ir.ReduceOp, "fold": ir.FoldOp, "resolve": ir.ResolveOp, "equijoin": ir.EquijoinOp}


#: Names that users may write for the fields of operators.
ALIASES = {
    "map": {"name": "task", "drop_keys": "drop"},
    "parallel_map": {"names": "tasks"},
    "filter": {"name": "task"},
    "unnest": {"unnest_key": "col"},
    "split": {"split_key": "key"},
    "gather": {"content_key": "content", "peripheral_chunks": "peripheral", "split": "name"},
    "reduce": {"reduce_key": "keys"},
}


def load_pipeline(path_or_dict: str | dict, registry: dict[str, Any]):
    """A pipeline from a YAML or JSON file or a dict.

    Operations have a ``type`` and the fields of their operator. ``"@name"`` stands for what
    the registry has under that name: tasks, functions, models. Names of tasks may also be
    written plainly where a task is meant.
    """
    from ..operators import Peripheral, Side
    from ..plans import ir

    spec = path_or_dict
    if isinstance(spec, str):
        text = Path(spec).read_text()
        if spec.endswith(".json"):
            spec = json.loads(text)
        else:
            import yaml

            spec = yaml.safe_load(text)

    def value(x, name):
        if isinstance(x, str) and x.startswith("@"):
            return registry[x[1:]]
        if name in ("task", "tasks") or (name in ("summarise", "compare") and isinstance(x, str)):
            return registry[x] if isinstance(x, str) else tuple(value(v, name) for v in x)
        if name == "peripheral":
            return Peripheral(**{s: Side(**v) for s, v in (x or {}).items()})
        if name == "keys" and isinstance(x, str):
            return (x,)
        return tuple(value(v, "") for v in x) if isinstance(x, list) else x

    ops = []
    for o in spec["operations"]:
        kind = o["type"]
        if kind not in _kinds():
            raise ValueError(f"unknown operation type: {kind}")
        cls, known = _kinds()[kind], ALIASES.get(kind, {})
        given = {known.get(k, k): v for k, v in o.items() if k != "type" and k != "method_kwargs"} | o.get("method_kwargs", {})
        if kind == "reduce" and "summarise" not in given:
            given["summarise"] = given["name"]
        if kind == "resolve" and "compare" not in given:
            given["compare"] = given.pop("name")
        if extra := set(given) - {f.name for f in fields(cls)}:
            raise ValueError(f"unknown fields of {kind}: {sorted(extra)}")
        ops.append(cls(**{k: value(v, k) for k, v in given.items()}))
    return ir.Pipeline(tuple(ops), tuple(spec.get("rewritten_by", ())))


def describe_pipeline(plan) -> tuple[dict, dict[str, Any]]:
    """What :func:`load_pipeline` reads, and the registry of tasks, functions and models that it names."""
    from ..model import Task
    from ..operators import Peripheral
    from ..plans.ir import identity

    registry: dict[str, Any] = {}

    def named(x, hint):
        base = hint.strip("<>") or "part"
        name, i = base, 2
        while name in registry and identity(registry[name]) != identity(x):
            name, i = f"{base}.{i}", i + 1
        registry[name] = x
        return "@" + name

    def plain(x, hint):
        if x is None or isinstance(x, (str, int, float, bool)):
            return x
        if isinstance(x, Task):
            return named(x, x.name)
        if isinstance(x, Peripheral):
            return {s: {f.name: getattr(side, f.name) for f in fields(side)} for s in ("previous", "next") if (side := getattr(x, s))}
        if isinstance(x, (tuple, list)):
            return [plain(v, hint) for v in x]
        return named(x, hint)

    types = {cls: kind for kind, cls in _kinds().items()}
    out = []
    for op in plan.ops:
        one = {"type": types[type(op)]}
        for f in fields(op):
            v = getattr(op, f.name)
            default = f.default if f.default is not MISSING else f.default_factory() if f.default_factory is not MISSING else MISSING
            if default is MISSING or not (v is default or (not is_dataclass(v) and not callable(v) and v == default)):
                one[f.name] = plain(v, f"{getattr(op, 'name', None) or getattr(op, 'key', None) or one['type']}.{f.name}")
        out.append(one)
    return {"operations": out, "rewritten_by": list(plan.trail)}, registry


def save_pipeline(plan, path: str) -> dict[str, Any]:
    """The optimised pipeline as a readable file with the trail of its rewrites; returns the registry to load it with."""
    spec, registry = describe_pipeline(plan)
    if path.endswith(".json"):
        Path(path).write_text(json.dumps(spec, indent=1))
    else:
        import yaml

        Path(path).write_text(yaml.safe_dump(spec, sort_keys=False))
    return registry


def build(path_in: str, path_out: str, registry: dict[str, Any], df: DataFrame, search) -> dict[str, Any]:
    """Optimise the pipeline of one file and write the result as another; returns the registry to load it with."""
    from ..plans.optimizer import optimize

    return save_pipeline(optimize(load_pipeline(path_in, registry), df, search), path_out)
