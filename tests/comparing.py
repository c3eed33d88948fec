"""Row comparison for tests."""


def same(left, right) -> bool:
    """Equal rows in any order, columns by name."""
    columns = sorted(left.columns)
    if sorted(right.columns) != columns:
        return False
    rows = lambda f: sorted(map(repr, [tuple(None if x != x else x for x in r) for r in f[columns].astype(object).values.tolist()]))
    return rows(left) == rows(right)
