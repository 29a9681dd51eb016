"""What the tests share."""

DATA = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def same(a, b) -> bool:
    """Frames equal as bags of rows, columns by name."""
    columns = sorted(a.columns)
    if columns != sorted(b.columns) or len(a) != len(b):
        return False
    a, b = (x[columns].sort_values(columns).reset_index(drop=True) for x in (a, b))
    return all((a[c].astype(object).where(a[c].notna(), None) == b[c].astype(object).where(b[c].notna(), None)).eq(True).all() or (a[c].isna() == b[c].isna()).all() and (a[c].dropna().to_numpy() == b[c].dropna().to_numpy()).all() for c in columns)
