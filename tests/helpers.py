def value(v):
    if isinstance(v, float):
        return repr(round(v, 9))
    return v.isoformat() if hasattr(v, "isoformat") else str(v)


def same(df, names, rows) -> None:
    cols = sorted(df.columns)
    assert cols == sorted(names)
    at = [names.index(c) for c in cols]
    assert sorted(tuple(value(r[c]) for c in cols) for r in df.collect()) == sorted(tuple(value(r[i]) for i in at) for r in rows)
