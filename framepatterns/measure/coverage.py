"""Which operators of a serial dataframe API are here, and on which pattern each runs.

Every name is listed under the function (or method of the engine) that serves it; ``served`` looks all of them
up, so a name without a function is an error and not a claim.
"""

from __future__ import annotations

import importlib

from pyspark.sql import Column, DataFrame

#: Operators of a serial dataframe API (public documentation), by pattern and by what serves them here.
#: A path is module.function of this package; "frame.x" and "column.x" are methods of the engine's own classes.
COVERED: dict[str, dict[str, str]] = {
    "row-local": {
        "operators.rows.map_scalar": "add sub mul div mod pow",
        "operators.rows.map_columns": "assign apply_expression floordiv radd rsub rmul rdiv eq ne lt le gt ge abs round",
        "operators.rows.row_agg": "any_row all_row sum_row mean_row min_row max_row std_row count_row",
        "operators.rows.select_rows": "filter query loc_condition",
        "operators.rows.project": "getitem drop pop insert loc_columns get",
        "operators.rows.project_types": "select_dtypes",
        "operators.rows.rename": "rename add_prefix add_suffix",
        "operators.rows.clip": "clip",
        "operators.rows.mask": "mask where",
        "operators.rows.sample_rows": "sample",
        "functions.kernel.local": "map_partitions pipe",
        "functions.udf.scalar": "map applymap transform_scalar",
        "functions.udf.missing_filled": "fillna",
        "column.isin": "isin", "column.between": "between", "column.isNull": "isna isnull", "column.isNotNull": "notna notnull", "column.cast": "astype",
        "frame.dropna": "dropna", "frame.replace": "replace",
    },
    "shuffle-compute": {
        "operators.joining.join": "merge join",
        "operators.setops.union_rows": "concat append", "operators.setops.difference": "difference", "operators.setops.intersection": "intersection", "operators.setops.symmetric_difference": "symmetric_difference",
        "operators.grouping.groupby": "groupby_median groupby_quantile groupby_nunique groupby_mode groupby_list",
        "operators.grouping.group_apply": "groupby_apply", "operators.grouping.group_transform": "groupby_transform", "operators.grouping.group_filter": "groupby_filter",
        "operators.ordering.top_k_per_key": "groupby_rank groupby_head groupby_nlargest",
        "operators.reshape.transpose": "transpose T", "operators.reshape.pivot": "pivot pivot_table unstack", "operators.reshape.melt": "melt stack",
        "operators.joining.salted_join": "merge_skewed",
    },
    "combine-shuffle-reduce": {
        "patterns.combine_shuffle_reduce": "groupby_sum groupby_mean groupby_min groupby_max groupby_count groupby_size groupby_std groupby_var groupby_prod groupby_any groupby_all groupby_first groupby_last value_counts",
        "operators.grouping.unique": "drop_duplicates unique", "operators.grouping.duplicated": "duplicated",
    },
    "broadcast-compute": {"operators.joining.broadcast_join": "merge_small lookup", "operators.joining.theta_join": "merge_condition", "operators.joining.range_join": "merge_interval"},
    "globally-reduce": {
        "operators.columnagg.column_agg": "sum mean min max count std var prod any all median quantile nunique skew kurt agg mode",
        "operators.columnagg.pair_agg": "cov corr", "operators.columnagg.describe": "describe", "operators.columnagg.length": "len shape size", "operators.columnagg.frames_equal": "equals", "frame.isEmpty": "empty",
    },
    "globally-ordered": {
        "operators.ordering.sort": "sort_values sort_index", "operators.ordering.top_k": "nlargest nsmallest head", "operators.ordering.rank": "rank",
        "operators.joining.asof_join": "merge_asof", "layout.rebalance.with_position": "reset_index", "layout.rebalance.rebalance": "repartition",
    },
    "halo": {
        "operators.windows.rolling": "rolling_sum rolling_mean rolling_min rolling_max rolling_count rolling_std rolling_var rolling_median rolling_apply_expression",
        "operators.windows.rolling_time": "rolling_time", "operators.windows.expanding": "expanding_sum expanding_mean expanding_min expanding_max expanding_count",
        "operators.windows.cumulate": "cumsum cummin cummax cumprod", "operators.windows.shift": "shift", "operators.windows.diff": "diff", "operators.windows.pct_change": "pct_change",
        "operators.windows.fill_forward": "ffill", "operators.windows.fill_backward": "bfill", "operators.windows.interpolate": "interpolate",
    },
    "partitioned-io": {
        "sources.readers.read_partitioned": "read_csv read_json read_parquet read_orc read_text", "sources.writers.write_partitioned": "to_csv to_json to_parquet to_orc to_text",
        "sources.readers.rows_to_frame": "from_records", "collectives.gather": "to_arrow to_records",
    },
    "layout": {"model.Frame.to_labels": "set_index", "model.Frame.from_labels": "index", "frame.columns": "columns", "frame.dtypes": "dtypes"},
}
#: Size of the reference API.
LISTED = 240


def _found(path: str) -> object:
    head, _, name = path.rpartition(".")
    if head in ("column", "frame"):
        return getattr({"column": Column, "frame": DataFrame}[head], name)
    owner, _, inner = head.rpartition(".")
    if inner[:1].isupper():
        return getattr(getattr(importlib.import_module(f"framepatterns.{owner}"), inner), name)
    return getattr(importlib.import_module(f"framepatterns.{head}"), name)


def served() -> dict[str, object]:
    """Operator to the function that serves it; raises if one of the functions does not exist."""
    return {name: _found(path) for by in COVERED.values() for path, names in by.items() for name in names.split()}


def coverage() -> list[tuple[str, int]]:
    """(pattern, operators that it serves)."""
    served()
    return [(p, len({n for names in by.values() for n in names.split()})) for p, by in COVERED.items()]


def coverage_share() -> float:
    """Operators served, as a share of the reference API's size."""
    return len(served()) / LISTED
