"""Order-insensitive comparison of a Spark result with a DuckDB result."""

import decimal


def _norm(v):
    if isinstance(v, bool) or v is None:
        return str(v)
    if isinstance(v, (int, float, decimal.Decimal)):
        return float(f"{float(v):.9g}")
    if isinstance(v, (list, tuple)):
        return tuple(_norm(x) for x in v)
    return str(v)


def same(df, relation):
    columns = sorted(df.columns)
    names = [d[0] for d in relation.description]
    assert columns == sorted(names)
    ours = sorted((tuple(_norm(r[c]) for c in columns) for r in df.collect()), key=str)
    at = [names.index(c) for c in columns]
    theirs = sorted((tuple(_norm(r[i]) for i in at) for r in relation.fetchall()), key=str)
    assert ours == theirs
