"""A rule program as a table function: SELECT * FROM rule_program(TABLE(edges), 'program', 'edge', 'path')."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ruleweave.lang.normalize import canonical
from ruleweave.lang.parser import parse
from ruleweave.operators import local

MOST_ROWS = 1_000_000


@udtf(returnType="a bigint, b bigint")
class RuleProgram:
    """Evaluates a program over one partition of a two-column BIGINT table; partition the table by component for large inputs."""

    def __init__(self):
        self.rows: list[tuple] = []

    def eval(self, row, text: str, relation: str, output: str):
        if len(self.rows) >= MOST_ROWS:
            raise ValueError(f"more than {MOST_ROWS} rows in one partition; partition the table argument further")
        self.rows.append(tuple(row[k] for k in range(2)))
        self.program, self.relation, self.output = text, relation, output

    def terminate(self):
        if self.rows:
            yield from sorted(local.evaluate(canonical(parse(self.program)), {self.relation: set(self.rows)})[self.output])


def register(spark: SparkSession, name: str = "rule_program") -> None:
    spark.udtf.register(name, RuleProgram)
