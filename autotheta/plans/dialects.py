"""The few expressions that Spark SQL and DuckDB write differently, so that a fixture has one definition."""

from __future__ import annotations


class Spark:
    name = "spark"

    def __init__(self, sf_dir: str):
        self.sf_dir = sf_dir

    def table(self, name: str) -> str:
        return f"parquet.`{self.sf_dir}/{name}.parquet`"

    def h(self, x: str, digits: int = 6) -> str:
        return f"cast(conv(substr(md5({x}), 1, {digits}), 16, 10) AS bigint)"

    def words(self, x: str) -> str:
        return f"filter(split(lower({x}), '[^\\\\p{{L}}\\\\p{{N}}]+'), w -> w <> '')"

    def split(self, x: str, pattern: str) -> str:
        return f"filter(split({x}, '{pattern}'), w -> w <> '')"

    def explode(self, x: str) -> str:
        return f"explode({x})"

    def head(self, x: str, n: int) -> str:
        return f"slice({x}, 1, {n})"

    def join(self, x: str) -> str:
        return f"array_join({x}, ' ')"

    def size(self, x: str) -> str:
        return f"size({x})"

    def where(self, x: str, v: str, cond: str) -> str:
        return f"filter({x}, {v} -> {cond})"

    def matches(self, x: str, pattern: str) -> str:
        return f"{x} RLIKE '^({pattern})$'"

    def div(self, a: str, b: int) -> str:
        return f"({a} div {b})"

    def text(self, x: str) -> str:
        return f"cast({x} AS string)"

    def extract(self, x: str, pattern: str) -> str:
        return f"regexp_extract({x}, '{pattern}', 1)"


class Duck(Spark):
    name = "duckdb"

    def __init__(self):
        super().__init__("")

    def table(self, name: str) -> str:
        return name

    def h(self, x: str, digits: int = 6) -> str:
        return f"('0x' || substr(md5({x}), 1, {digits}))::BIGINT"

    def words(self, x: str) -> str:
        return f"list_filter(string_split_regex(lower({x}), '[^\\p{{L}}\\p{{N}}]+'), lambda w: w <> '')"

    def split(self, x: str, pattern: str) -> str:
        return f"list_filter(string_split_regex({x}, '{pattern}'), lambda w: w <> '')"

    def explode(self, x: str) -> str:
        return f"unnest({x})"

    def head(self, x: str, n: int) -> str:
        return f"({x})[1:{n}]"

    def join(self, x: str) -> str:
        return f"array_to_string({x}, ' ')"

    def size(self, x: str) -> str:
        return f"len({x})"

    def where(self, x: str, v: str, cond: str) -> str:
        return f"list_filter({x}, lambda {v}: {cond})"

    def matches(self, x: str, pattern: str) -> str:
        return f"regexp_full_match({x}, '{pattern}')"

    def div(self, a: str, b: int) -> str:
        return f"({a} // {b})"

    def text(self, x: str) -> str:
        return f"cast({x} AS VARCHAR)"

    def extract(self, x: str, pattern: str) -> str:
        return f"regexp_extract({x}, '{pattern}', 1)"
