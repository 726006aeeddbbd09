"""Small inputs that every operator on documents must take."""

DOCS = "doc_id long, text string, lang string, source string, n_chars long, size long, key string"


def docs_frame(spark, texts, ids=None, sources=None, langs=None):
    """Documents with two extra columns whose names clash with operators' own."""
    ids = list(range(len(texts))) if ids is None else ids
    rows = [
        (i, t, (langs or {}).get(i, "en") if isinstance(langs, dict) else (langs[k] if langs else "en"), sources[k] if sources else f"s{k % 3}", len(t or ""), -1, "x")
        for k, (i, t) in enumerate(zip(ids, texts))
    ]
    return spark.createDataFrame(rows, DOCS)


def odd_texts():
    """Null, empty, blank, very long, tied and repeated texts."""
    long = " ".join(f"w{i % 977}x{i % 31}" for i in range(60_000))
    return [None, "", "   \n\t ", "one", "one two", "one two three", "one two three", "One TWO three", long, long + " tail", "é ñ ß 漢字 \U0001f600", "a b c"]
