"""Small vocabulary for SQL text that both Spark and DuckDB can run.

Rules and features are written once as expressions over this vocabulary.  Operators turn the Spark form into Columns
with `expr`; oracles and tests run the other form on the same Parquet files.
"""

from __future__ import annotations


def quote(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


class SparkSql:
    name = "spark"

    def lit(self, text):
        return "'" + text.replace("\\", "\\\\").replace("'", "\\'").replace("\n", "\\n") + "'"

    def digest_int(self, text):
        return f"cast(conv(substr(md5({text}), 1, 4), 16, 10) as int)"

    def digest31(self, text):
        return f"(cast(conv(substr(md5({text}), 1, 8), 16, 10) as bigint) & 2147483647)"

    def find_all(self, text, pattern):
        return f"regexp_extract_all({text}, {self.lit(pattern)}, 0)"

    def extract(self, text, pattern, group=1):
        return f"regexp_extract({text}, {self.lit(pattern)}, {group})"

    def matches(self, text, pattern):
        return f"(({text}) rlike {self.lit(pattern)})"

    def occurrences(self, text, pattern):
        return f"regexp_count({text}, {self.lit(pattern)})"

    def replace(self, text, pattern, by):
        return f"regexp_replace({text}, {self.lit(pattern)}, {self.lit(by)})"

    def each(self, items, var, body):
        return f"transform({items}, {var} -> {body})"

    def indexed(self, items, var, pos, body):
        """`pos` counts from 1."""
        return f"transform({items}, ({var}, {pos}0) -> {body.replace('{' + pos + '}', f'({pos}0 + 1)')})"

    def keep(self, items, var, cond):
        return f"filter({items}, {var} -> {cond})"

    def join(self, items, by):
        return f"array_join({items}, {self.lit(by)})"

    def part(self, items, start, count):
        return f"slice({items}, {start}, {count})"

    def size(self, items):
        return f"size({items})"

    def at(self, items, i):
        return f"try_element_at({items}, {i})"

    def split(self, text, by):
        return f"split({text}, {self.lit(by)}, -1)"

    def distinct(self, items):
        return f"array_distinct({items})"

    def common(self, a, b):
        return f"array_intersect({a}, {b})"

    def extend(self, *lists):
        return f"concat({', '.join(lists)})"

    def array(self, *items):
        return f"array({', '.join(items)})"

    def no_strings(self):
        return "cast(array() as array<string>)"

    def range(self, n):
        """1..n as an array; n is a constant."""
        return f"sequence(1, {n})"

    def texts(self):
        return "string"

    def double(self, x):
        return f"cast({x} as double)"


class DuckSql(SparkSql):
    name = "duckdb"

    def lit(self, text):
        return " || chr(10) || ".join(quote(p) for p in text.split("\n")).join("()") if "\n" in text else quote(text)

    def digest_int(self, text):
        return f"cast('0x' || substr(md5({text}), 1, 4) as int)"

    def digest31(self, text):
        return f"(cast('0x' || substr(md5({text}), 1, 8) as bigint) & 2147483647)"

    def find_all(self, text, pattern):
        return f"regexp_extract_all({text}, {self.lit(pattern)})"

    def matches(self, text, pattern):
        return f"regexp_matches({text}, {self.lit(pattern)})"

    def occurrences(self, text, pattern):
        return f"len(regexp_extract_all({text}, {self.lit(pattern)}))"

    def replace(self, text, pattern, by):
        return f"regexp_replace({text}, {self.lit(pattern)}, {self.lit(by)}, 'g')"

    def each(self, items, var, body):
        return f"list_transform({items}, lambda {var}: {body})"

    def indexed(self, items, var, pos, body):
        return f"list_transform({items}, lambda {var}, {pos}: {body.replace('{' + pos + '}', pos)})"

    def keep(self, items, var, cond):
        return f"list_filter({items}, lambda {var}: {cond})"

    def join(self, items, by):
        return f"array_to_string({items}, {self.lit(by)})"

    def part(self, items, start, count):
        return f"({items})[{start} : {start} + ({count}) - 1]"

    def size(self, items):
        return f"len({items})"

    def at(self, items, i):
        return f"({items})[{i}]"

    def split(self, text, by):
        return f"string_split({text}, {self.lit(by)})"

    def distinct(self, items):
        return f"list_distinct({items})"

    def common(self, a, b):
        return f"list_intersect({a}, {b})"

    def extend(self, *lists):
        out = lists[0]
        for x in lists[1:]:
            out = f"list_concat({out}, {x})"
        return out

    def array(self, *items):
        return f"[{', '.join(items)}]"

    def no_strings(self):
        return "cast([] as varchar[])"

    def range(self, n):
        return f"generate_series(1, {n})"

    def texts(self):
        return "varchar"


SPARK, DUCK = SparkSql(), DuckSql()
