"""What tests share."""

SMALL = "/root/testdata/sf0.001"


def rows_of(df):
    """Rows as sorted tuples of text, columns by name; numbers to six places."""

    def text(v):
        if v is None or v != v:
            return ""
        if isinstance(v, bool):
            return str(v)
        try:
            return f"{float(v):.6g}"
        except (TypeError, ValueError):
            return str(v)

    columns = sorted(df.columns)
    return columns, sorted(tuple(text(v) for v in r) for r in df[columns].astype(object).where(df[columns].notna(), None).values.tolist())
