"""Edge rows that every operator on documents must take: nulls, empty and long texts, repeats, clashing columns."""

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, score string, fp string, n string"


def edge_docs(spark):
    rows = [
        (1, None, None, None, None), (2, "", "en", "src0", 0), (3, "one two three four five six seven", "en", "src0", 33),
        (4, "one two three four five six seven", "en", "src1", 33), (5, "x" * 50_000, "de", "src0", 50_000), (6, "  \n\t ", "fr", "src2", 5),
        (7, "日本語 ß é 123 <|endoftext|>", "fr", "src2", 26), (3, "one two three four five six seven", "en", "src0", 33),
        (8, "12345 !!! ...", "es", "other", 13), (None, "row without an id", "en", "src3", 17), (9, "word " * 30_000, "en", "src0", 150_000),
    ]
    return spark.createDataFrame([(*r, "clash", "clash", "clash") for r in rows], DOCS)


def no_docs(spark):
    return spark.createDataFrame([], DOCS)
