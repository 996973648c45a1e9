"""Documents that every operator must handle: nulls, empty and long texts, repeated rows, extra columns with clashing names."""

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, n_tokens bigint, group_size bigint, _text string"


def rows():
    prose = "the quick brown fox jumps over the lazy dog and then rests under a tall old tree near water "
    texts = [
        None,
        "",
        " \n\t ",
        "word",
        prose,
        prose,
        prose.upper(),
        prose * 40,
        prose * 40 + "tail",
        "x" * 70_000,
        "a  b\n\n c\t\td  \x1c\x85é́ ß Σ<|endoftext|> don't",
        "日本語テキスト、漢字 emoji 😀😀\nsecond line\nsecond line",
    ]
    out = [(i, t, None, None, None, 7, 7, "clash") for i, t in enumerate(texts)]
    return out + [(20, prose, "en", "src0", 5, 7, 7, "clash")]


def frame(spark):
    return spark.createDataFrame(rows(), SCHEMA)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)
