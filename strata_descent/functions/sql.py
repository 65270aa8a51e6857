"""The engine's functions for SQL users: scoring as temporary SQL functions, draws as a table function."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

#: Name, arguments, result and body; bodies are expressions that the optimiser sees through.
FUNCTIONS = (
    ("descent_dot", "a array<double>, b array<double>", "double", "aggregate(zip_with(a, b, (u, v) -> u * v), 0D, (s, v) -> s + v)"),
    ("descent_scores", "x array<double>, w array<array<double>>", "array<double>", "transform(w, r -> aggregate(zip_with(x, r, (u, v) -> u * v), 0D, (s, v) -> s + v))"),
    ("descent_class", "scores array<double>", "int", "cast(array_position(scores, array_max(scores)) - 1 as int)"),
    ("descent_loss", "scores array<double>, y int", "double", "array_max(scores) + ln(aggregate(scores, 0D, (a, v) -> a + exp(v - array_max(scores)))) - get(scores, y)"),
)


def register(spark: SparkSession) -> None:
    """Make the scoring functions and the table function descent_draws known to SQL in this session."""
    for name, arguments, result, body in FUNCTIONS:
        spark.sql(f"create or replace temporary function {name}({arguments}) returns {result} return {body}")
    spark.udtf.register("descent_draws", F.udtf(Draws, returnType="r int, pos bigint"))


class Draws:
    """descent_draws(seed, step, stratum, n_i, b_i): the positions that a step draws from a stratum; the same as the engine's."""

    def eval(self, seed: int, step: int, stratum: int, n_i: int, b_i: int):
        import hashlib

        for r in range(1, b_i + 1):
            digest = hashlib.md5(f"{seed}|{step}|{stratum}|{r}".encode(), usedforsecurity=False).hexdigest()
            yield r, int(digest[:13], 16) % n_i
