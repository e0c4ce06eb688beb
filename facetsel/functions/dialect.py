"""SQL fragments that Spark and DuckDB spell differently; everything else in the rubric is spelled alike."""

from __future__ import annotations

TOKEN_GAP = r"[ \n.,;:!?|#$%&*]+"


class Spark:
    name = "spark"

    def quoted(self, pattern: str) -> str:
        return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'").replace("\n", "\\n") + "'"

    def tokens(self, text: str) -> str:
        return f"array_remove(split(lower({text}), {self.quoted(TOKEN_GAP)}), '')"

    def size(self, array: str) -> str:
        return f"cast(size({array}) as bigint)"

    def kept(self, array: str, test: str) -> str:
        return f"filter({array}, x -> {test})"

    def where(self, array: str, test: str) -> str:
        return self.size(self.kept(array, test))

    def distinct(self, array: str) -> str:
        return f"array_distinct({array})"

    def common(self, a: str, b: str) -> str:
        return f"array_intersect({a}, {b})"

    def count(self, text: str, pattern: str) -> str:
        return f"cast(regexp_count({text}, {self.quoted(pattern)}) as bigint)"

    def div(self, a: str, b: str) -> str:
        return f"(({a}) div ({b}))"

    def tie(self, seed: int, key: str) -> str:
        return f"cast(conv(substring(md5(concat('{seed}|', {key})), 1, 15), 16, 10) as bigint)"


class Duck(Spark):
    name = "duckdb"

    def quoted(self, pattern: str) -> str:
        return "'" + pattern.replace("'", "''") + "'"

    def tokens(self, text: str) -> str:
        return f"list_filter(regexp_split_to_array(lower({text}), {self.quoted(TOKEN_GAP)}), lambda x: x <> '')"

    def size(self, array: str) -> str:
        return f"len({array})"

    def kept(self, array: str, test: str) -> str:
        return f"list_filter({array}, lambda x: {test})"

    def distinct(self, array: str) -> str:
        return f"list_distinct({array})"

    def common(self, a: str, b: str) -> str:
        return f"list_intersect({a}, {b})"

    def count(self, text: str, pattern: str) -> str:
        return f"len(regexp_extract_all({text}, {self.quoted(pattern)}))"

    def div(self, a: str, b: str) -> str:
        return f"(({a}) // ({b}))"

    def tie(self, seed: int, key: str) -> str:
        return f"CAST('0x' || substr(md5('{seed}|' || {key}), 1, 15) AS BIGINT)"


SPARK, DUCK = Spark(), Duck()
