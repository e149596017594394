"""SQL that solves small linear systems by elimination, for the engines that check the ridge weights."""

from __future__ import annotations


def _fix(c: str) -> str:
    return f"round({c} * 1000000)::BIGINT"


def _eliminated(start: str, z: int, width: int, name: str) -> tuple[list[str], str]:
    """CTEs that bring the columns m<i>_<j> of {name}_0 (a z x z system, `width` right sides) to triangular form."""
    steps = [start]
    for k in range(z - 1):
        row = [f"m{i}_{j} - m{i}_{k} * m{k}_{j} / m{k}_{k} AS m{i}_{j}" if i > k and j > k else f"m{i}_{j}" for i in range(z) for j in range(z + width)]
        steps.append(f"{name}_{k + 1} AS (SELECT {', '.join(row)} FROM {name}_{k})")
    return steps, f"{name}_{z - 1}"


def _back(steps: list[str], last: str, z: int, right: list[tuple[int, str]], name: str) -> str:
    """Back substitution; right: (column of the right side, prefix of the unknowns)."""
    for column, x in right:
        for i in reversed(range(z)):
            known = "".join(f" - m{i}_{j} * {x}{j}" for j in range(i + 1, z))
            steps.append(f"{name}_{x}{i} AS (SELECT *, (m{i}_{column}{known}) / m{i}_{i} AS {x}{i} FROM {last})")
            last = f"{name}_{x}{i}"
    return last


def elimination(source: str, marks: list[str], y: str, penalty: float, name: str) -> str:
    """CTEs that solve the ridge normal equations of `source`: {name}, one row of w_<mark>."""
    z = len(marks)
    cell = lambda i, j: f"sum({_fix(marks[i])} * {_fix(marks[j] if j < z else y)})::DOUBLE / 1e12" + (f" + {penalty}" if i == j else "")
    start = f"{name}_0 AS (SELECT " + ", ".join(f"{cell(i, j)} AS m{i}_{j}" for i in range(z) for j in range(z + 1)) + f" FROM {source})"
    steps, last = _eliminated(start, z, 1, name)
    last = _back(steps, last, z, [(z, "w")], name)
    steps.append(f"{name} AS MATERIALIZED (SELECT {', '.join(f'w{i} AS w_{m}' for i, m in enumerate(marks))} FROM {last})")
    return ", ".join(steps)


def inverse(source: str, marks: list[str], penalty: float, name: str) -> str:
    """CTEs of the inverse of the ridge system: {name}, one row of v_<mark>_<mark>."""
    z = len(marks)
    cell = lambda i, j: (f"sum({_fix(marks[i])} * {_fix(marks[j])})::DOUBLE / 1e12" + (f" + {penalty}" if i == j else "")) if j < z else f"{1.0 if j - z == i else 0.0}::DOUBLE"
    start = f"{name}_0 AS (SELECT " + ", ".join(f"{cell(i, j)} AS m{i}_{j}" for i in range(z) for j in range(2 * z)) + f" FROM {source})"
    steps, last = _eliminated(start, z, z, name)
    last = _back(steps, last, z, [(z + k, f"x{k}y") for k in range(z)], name)
    steps.append(f"{name} AS MATERIALIZED (SELECT {', '.join(f'x{k}y{i} AS v_{a}_{b}' for k, b in enumerate(marks) for i, a in enumerate(marks))} FROM {last})")
    return ", ".join(steps)
