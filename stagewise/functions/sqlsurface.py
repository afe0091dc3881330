"""Filters in SQL text."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..plans.storage import keep
from .hashing import SEGMENT_SALT
from .theory import C_UNIFORM


def register(spark: SparkSession, name: str, handle) -> Callable[[str], str]:
    """A view ``filter_<name>``, a function ``segment_of_<name>(key)``, and the predicate's text for a key; single long keys.

    The predicate is for a row joined with the view under the alias ``f``.
    """
    view = keep(handle.segments.select("seg", "n", "u", "stages", "tail"))
    view.createOrReplaceTempView(f"filter_{name}")
    half = f"shiftrightunsigned(xxhash64(CAST({SEGMENT_SALT} AS BIGINT), key), 33)"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION segment_of_{name}(key BIGINT) RETURNS INT RETURN CAST(shiftrightunsigned({half} * {handle.parts}, 31) AS INT)")
    if handle.spec.mode != "and" or [s.kind for s in handle.spec.stages] not in (["xor", "retrieval"], ["retrieval"]):
        raise ValueError("SQL text is there for XOR tables")

    def below(seed: str, n: str, key: str) -> str:
        return f"shiftrightunsigned(shiftrightunsigned(xxhash64({seed}, {key}), 33) * {n}, 31)"

    def cell(s: str, at: str) -> str:
        word = lambda i: f"get({s}.words, CAST(shiftright({at} * {s}.width, 6) AS INT) + {i})"
        off = f"CAST(({at} * {s}.width) & 63 AS INT)"
        return f"((shiftrightunsigned({word(0)}, {off}) | shiftleft(shiftleft({word(1)}, 1), 63 - {off})) & (shiftleft(1L, {s}.width) - 1))"

    def table(i: int, key: str) -> str:
        s = f"get(f.stages, {i})"
        block = f"floor({s}.m / 3)"
        cells = " ^ ".join(cell(s, f"({j} * {block} + {below(f'{s}.seed + {j}L', block, key)})") for j in range(3))
        width = f"{s}.width" if handle.spec.stages[i].kind == "xor" else "1"
        return f"(({cells}) = (xxhash64({s}.seed + 9L, {key}) & (shiftleft(1L, {width}) - 1)))"

    def predicate(key: str) -> str:
        text = " AND ".join(table(i, key) for i in range(len(handle.spec.stages)))
        return f"({'NOT ' if handle.spec.negate else ''}({text}))"

    return predicate


def register_explain(spark: SparkSession, name: str, handle) -> None:
    """A view ``stages_of_<name>`` (a row a stage: its bits and what the plan needs) and the table function ``explain_filter`` for it."""

    class Explain:
        def eval(self, row):
            kind, eps, n, C = row["kind"], row["eps"], row["n"], row["C"]
            stored = n if eps > 0 else n + row["passing"]
            per_key = -math.log2(eps) / math.log(2) if kind in ("bloom", "blocked") else 1.05 * (2 - math.log2(eps)) if kind == "cuckoo" else C * max(1, round(-math.log2(eps))) if eps > 0 else {"edge_map": 2.33, "colour_map": 2.2}.get(kind, C)
            yield row["stage"], kind, eps, float(stored), per_key * stored, float(row["bits"])

    spec, n, u = handle.spec, handle.n, handle.u
    n, u = (u - n, u) if spec.negate else (n, u)
    left, rows = float(u - n), []
    bits = {r["stage"]: r["bits"] for r in handle.space().collect()}  # a row a stage
    for i, s in enumerate(spec.stages):
        rows.append((i, s.kind, float(s.eps), n, u, left, C_UNIFORM, int(bits.get(i, 0))))
        left *= s.eps
    spark.createDataFrame(rows, "stage int, kind string, eps double, n long, u long, passing double, C double, bits long").createOrReplaceTempView(f"stages_of_{name}")
    spark.udtf.register("explain_filter", udtf(Explain, returnType="stage int, kind string, eps double, keys double, planned double, bits double"))
