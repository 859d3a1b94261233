"""Frames that every operator must stand: nulls, empty and long texts, repeats, clashing columns, nothing at all."""

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def odd_docs(spark, word="word "):
    long = " ".join(f"w{k * 7919 % 10007}" for k in range(20_000))
    rows = [
        (1, "the quick brown fox jumps over the lazy dog near the river bank today", "en", "s", 1),
        (2, "the quick brown fox jumps over the lazy dog near the river bank today", None, None, None),
        (2, "the quick brown fox jumps over the lazy dog near the river bank today", None, None, None),
        (3, None, "en", "s", 0), (4, "", "en", "s", 0), (None, "no id here", "en", "s", 1), (None, None, None, None, None),
        (5, long, "en", "s", 1), (6, " \n\t ", "en", "s", 1), (7, "é　ß 漢字 \x00 ퟿", "xx", "s", 1), (8, word * 300, "en", "s", 1), (9, "a", "en", "s", 1),
    ]
    extra = "fp long, fingerprint string, component_id long, data binary, mark long, u long, v long, _rank long, score double, h long, shard int, spans string, length long"
    names = [f.split()[0] for f in extra.split(", ")]
    frame = spark.createDataFrame(rows, DOCS)
    for f in extra.split(", "):
        name, kind = f.split()
        frame = frame.selectExpr("*", f"cast(null as {kind}) as {name}")
    assert set(names) <= set(frame.columns)
    return frame


def no_docs(spark):
    return spark.createDataFrame([], DOCS)
