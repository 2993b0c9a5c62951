import math


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else repr(v + 0.0)
    if isinstance(v, (list, tuple)):
        return [plain(x) for x in v]
    return v


def same_rows(df, con, sql):
    """Assert that a frame and a DuckDB query have the same columns and multiset of rows; returns the number of rows."""
    rows, columns = df.collect(), df.columns
    result = con.execute(sql)
    names = [d[0] for d in result.description]
    other = result.fetchall()
    assert sorted(columns) == sorted(names)
    order = sorted(columns)
    ours = sorted(str([plain(r[c]) for c in order]) for r in rows)
    theirs = sorted(str([plain(r[names.index(c)]) for c in order]) for r in other)
    assert len(ours) == len(theirs)
    assert ours == theirs, next((a, b) for a, b in zip(ours, theirs) if a != b)
    return len(ours)
