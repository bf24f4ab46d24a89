"""Comparing frames with tables of another engine."""


def same_rows(frame, table):
    """Rows of a Spark frame and a DuckDB relation, in any order."""
    columns = sorted(frame.columns)
    assert columns == sorted(table.columns)
    plain = lambda v: float(v) if isinstance(v, (int, float)) and not isinstance(v, bool) else v
    a = sorted(repr([plain(v) for v in r]) for r in frame.select(*columns).collect())
    b = sorted(repr([plain(v) for v in r]) for r in table.project(", ".join(f'"{c}"' for c in columns)).fetchall())
    assert a == b
