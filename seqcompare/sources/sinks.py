"""Where matrices, statistics and trees go."""

from __future__ import annotations

from pyspark.sql import DataFrame

#: A square text matrix is put together on the driver up to so many sequences.
MAX_SQUARE = 5_000


def write(df: DataFrame, path: str, fmt: str = "parquet", by: tuple[str, ...] = (), mode: str = "errorifexists") -> None:
    df.write.mode(mode).partitionBy(*by).format(fmt).save(path)


def phylip(square: DataFrame) -> str:
    """The square matrix as text: the number of sequences, then a name and its row on each line."""
    n = square.select("i").distinct().limit(MAX_SQUARE + 1).count()
    if n > MAX_SQUARE:
        raise ValueError(f"a square of more than {MAX_SQUARE} sequences isn't put together here: write the rows")
    rows: dict[str, dict[str, float]] = {}
    for r in square.select("i", "j", "value").toLocalIterator():
        rows.setdefault(r.i, {})[r.j] = r.value
    names = sorted(rows)
    return "\n".join([str(len(names)), *(" ".join([a.replace(" ", "_"), *(f"{rows[a][b]:.6f}" if rows[a].get(b) is not None else "nan" for b in names)]) for a in names)]) + "\n"


def newicks(trees: DataFrame, path: str) -> None:
    trees.select("newick").write.text(path)
