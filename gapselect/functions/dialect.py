"""View definitions are written once and rendered for Spark SQL or for DuckDB."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Dialect:
    spark: bool

    def table(self, name: str) -> str:
        return "{" + name + "}" if self.spark else name

    def coin(self, text: str, first: int, digits: int) -> str:
        """Hex digits of md5 as an integer: the same bits in both engines."""
        part = f"substr(md5({text}), {first + 1}, {digits})"
        return f"CAST(conv({part}, 16, 10) AS BIGINT)" if self.spark else f"CAST('0x' || {part} AS BIGINT)"

    def xor(self, a: str, b: str) -> str:
        return f"(({a}) ^ ({b}))" if self.spark else f"xor({a}, {b})"

    def count_of(self, text: str, pattern: str) -> str:
        return f"regexp_count({text}, '{pattern}')" if self.spark else f"len(regexp_extract_all({text}, '{pattern}'))"

    def words(self, text: str) -> str:
        return f"size(split({text}, ' '))" if self.spark else f"len(string_split({text}, ' '))"

    def distinct_words(self, text: str) -> str:
        return f"size(array_distinct(split({text}, ' ')))" if self.spark else f"len(list_distinct(string_split({text}, ' ')))"

    def days(self, start: str, end: str) -> str:
        return f"datediff({end}, {start})" if self.spark else f"date_diff('day', CAST({start} AS DATE), CAST({end} AS DATE))"


SPARK, DUCK = Dialect(True), Dialect(False)


def floor_div(x: str, y: str) -> str:
    return f"CAST(floor(({x}) / ({y})) AS INT)"


def clip(x: str, low: int = 0, high: int = 8) -> str:
    return f"least({high}, greatest({low}, {x}))"
