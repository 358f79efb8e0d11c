"""Declared schemas; every public function checks its input against one of them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql.types import StructType

from adapterlab.errors import SchemaMismatch

SAMPLES = "adapter_id string, sample_id bigint, dataset string, tok_len bigint, order_key string"
ADAPTERS = "adapter_id string, dataset string, rank int, alpha double, dropout double, global_batch_size int, seed bigint"
ITEMS = "group_id int, gb bigint, bin int, adapter_id string, sample_id bigint, tok_len bigint"
SCHEDULE = "pos bigint, group_id int, gb bigint, bin int, is_noop boolean, padded_tokens bigint, real_tokens bigint"
X_ROWS = "row_id bigint, adapter_id string, x array<bigint>"
RUNS = "run_id string, pos bigint, tokens bigint"


def require(df: DataFrame, schema: str, what: str = "input") -> DataFrame:
    """The declared columns of `df` in their order; raises SchemaMismatch if one is missing or of another type."""
    have = {f.name: f.dataType.simpleString() for f in df.schema.fields}
    want = {f.name: f.dataType.simpleString() for f in StructType.fromDDL(schema).fields}
    wrong = [f"{n} {t} (found {have.get(n, 'nothing')})" for n, t in want.items() if have.get(n) != t]
    if wrong:
        raise SchemaMismatch(f"{what}: needs {', '.join(wrong)}")
    return df.select(*want)
