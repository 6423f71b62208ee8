"""Query functions and operators in each dialect: name -> (Spark, DuckDB) templates.

``{0}`` is the first argument, ``{*}`` all of them with commas.
"""

from __future__ import annotations

import math

BINARY = {"=": "=", "<>": "<>", "<": "<", ">": ">", "<=": "<=", ">=": ">=", "and": "AND", "or": "OR", "-": "-", "*": "*"}

#: name -> template for both, or (Spark, DuckDB)
FUNCTIONS: dict[str, str | tuple[str, str]] = {
    "not": "(NOT {0})",
    "neg": "(- {0})",
    "xor": "(({0}) <> ({1}))",
    "is null": "({0} IS NULL)",
    "is not null": "({0} IS NOT NULL)",
    "same": ("({0} <=> {1})", "({0} IS NOT DISTINCT FROM {1})"),
    "starts with": ("startswith({0}, {1})", "starts_with({0}, {1})"),
    "ends with": ("endswith({0}, {1})", "ends_with({0}, {1})"),
    "contains": "contains({0}, {1})",
    "=~": ("({0} RLIKE concat('^(?:', {1}, ')$'))", "regexp_full_match({0}, {1})"),
    "^": ("power({0}, {1})", "pow({0}, {1})"),
    "%": "({0} % {1})",
    "coalesce": "coalesce({*})",
    "nullif": "nullif({0}, {1})",
    "abs": "abs({0})",
    "ceil": "CAST(ceil({0}) AS DOUBLE)",
    "floor": "CAST(floor({0}) AS DOUBLE)",
    "round": "CAST(round({*}) AS DOUBLE)",
    "sqrt": "sqrt({0})",
    "exp": "exp({0})",
    "log": "ln({0})",
    "log10": "log10({0})",
    "sin": "sin({0})",
    "cos": "cos({0})",
    "sign": "CAST(sign({0}) AS BIGINT)",
    "pi": "pi()",
    "e": f"CAST({math.e!r} AS DOUBLE)",
    "as long": "CAST({0} AS BIGINT)",
    "tointeger": ("CAST(try_cast({0} AS DOUBLE) AS BIGINT)", "CAST(trunc(TRY_CAST({0} AS DOUBLE)) AS BIGINT)"),
    "tofloat": "try_cast({0} AS DOUBLE)",
    "tostring": ("CAST({0} AS STRING)", "CAST({0} AS VARCHAR)"),
    "toboolean": "try_cast({0} AS BOOLEAN)",
    "toupper": "upper({0})",
    "tolower": "lower({0})",
    "trim": "trim({0})",
    "ltrim": "ltrim({0})",
    "rtrim": "rtrim({0})",
    "replace": "replace({0}, {1}, {2})",
    "left": "left({0}, {1})",
    "right": "right({0}, {1})",
    "split": ("split({0}, concat('\\\\Q', {1}, '\\\\E'))", "string_split({0}, {1})"),
    "charlength": "length({0})",
    "listlength": ("size({0})", "len({0})"),
    "head": ("try_element_at({0}, 1)", "list_extract({0}, 1)"),
    "last": ("try_element_at({0}, -1)", "list_extract({0}, -1)"),
    "tail": ("slice({0}, 2, greatest(size({0}) - 1, 0))", "list_slice({0}, 2, len({0}))"),
    "reverse": ("reverse({0})", "list_reverse({0})"),
    "sort": ("array_sort({0})", "list_sort({0})"),
    "concat": ("concat({*})", "({0} || {1})"),
    "explode": ("explode({0})", "unnest({0})"),
    "array": ("array({*})", "[{*}]"),
    "member": ("array_contains({1}, {0})", "list_contains({1}, {0})"),
    "overlap": ("arrays_overlap({0}, {1})", "list_has_any({0}, {1})"),
    # an edge's identity as text, as the path iterations write it
    "id text": ("coalesce(replace(replace(CAST({0} AS STRING), '\\\\', '\\\\\\\\'), '|', '\\\\|'), '\\\\N')", "coalesce(replace(replace(CAST({0} AS VARCHAR), '\\', '\\\\'), '|', '\\|'), '\\N')"),
    "edge text": "concat_ws('|', {*})",
    "date": "CAST({0} AS DATE)",
    "localdatetime": ("CAST({0} AS TIMESTAMP_NTZ)", "CAST({0} AS TIMESTAMP)"),
    "datetime": ("CAST({0} AS TIMESTAMP_NTZ)", "CAST({0} AS TIMESTAMP)"),
    "date.truncate": ("CAST(date_trunc({0}, {1}) AS DATE)", "CAST(date_trunc({0}, {1}) AS DATE)"),
    "duration.days": ("CAST(datediff({1}, {0}) AS BIGINT)", "CAST(date_diff('day', CAST({0} AS DATE), CAST({1} AS DATE)) AS BIGINT)"),
    "json_int": ("CAST(get_json_object({0}, {1}) AS BIGINT)", "CAST(json_extract_string({0}, {1}) AS BIGINT)"),
    "json_float": ("CAST(get_json_object({0}, {1}) AS DOUBLE)", "CAST(json_extract_string({0}, {1}) AS DOUBLE)"),
    "json_text": ("get_json_object({0}, {1})", "json_extract_string({0}, {1})"),
    "json_time": ("CAST(get_json_object({0}, {1}) AS TIMESTAMP_NTZ)", "CAST(json_extract_string({0}, {1}) AS TIMESTAMP)"),
    "map_int": ("CAST(try_element_at({0}, {1}) AS BIGINT)", "CAST(map_extract_value({0}, {1}) AS BIGINT)"),
    "map_float": ("CAST(try_element_at({0}, {1}) AS DOUBLE)", "CAST(map_extract_value({0}, {1}) AS DOUBLE)"),
    "map_text": ("try_element_at({0}, {1})", "map_extract_value({0}, {1})"),
    "map_time": ("CAST(try_element_at({0}, {1}) AS TIMESTAMP_NTZ)", "CAST(map_extract_value({0}, {1}) AS TIMESTAMP)"),
    "url_host": ("parse_url({0}, 'HOST')", "regexp_extract({0}, '^[a-z]+://(?:[^/@]*@)?([^/:?#]+)', 1)"),
    "year": "CAST(year({0}) AS BIGINT)",
    "month": "CAST(month({0}) AS BIGINT)",
    "day": "CAST(day({0}) AS BIGINT)",
    "hour": "CAST(hour({0}) AS BIGINT)",
    "quarter": "CAST(quarter({0}) AS BIGINT)",
    # aggregates
    "count": "count({0})",
    "sum": "coalesce(sum({0}), 0)",
    "avg": "avg({0})",
    "min": "min({0})",
    "max": "max({0})",
    "stdev": "stddev_samp({0})",
    "stdevp": "stddev_pop({0})",
    "collect": ("collect_list({0})", "coalesce(list({0}) FILTER (({0}) IS NOT NULL), [])"),
    "percentilecont": ("percentile({0}, {1})", "quantile_cont({0}, {1})"),
    "percentiledisc": ("percentile_disc({1}) WITHIN GROUP (ORDER BY {0})", "quantile_disc({0}, {1})"),
    "count_distinct": "count(DISTINCT {0})",
    "sum_distinct": "coalesce(sum(DISTINCT {0}), 0)",
    "avg_distinct": "avg(DISTINCT {0})",
    "min_distinct": "min({0})",
    "max_distinct": "max({0})",
    "collect_distinct": ("collect_set({0})", "coalesce(list(DISTINCT {0}) FILTER (({0}) IS NOT NULL), [])"),
}
