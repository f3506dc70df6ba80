"""Small tables with every awkward row, shared by the tests of the operators."""

CLASHING = "doc_id long, text string, lang string, source string, n_chars long, fp string, name string, block string, share double, `count` long, label string, bucket long, rank long, one long, two long, doc long, txt long, pos long, blocks long, digest string, shard string, offset long, length long, y int, score double, weight double, pass_no int, rest long, size long, room long, u long, v long"
EXTRA = (None,) * 27

LONG = " ".join(f"word{k % 977} and{k % 31}" for k in range(30_000))
ROWS = [
    (1, "the quick brown fox jumps over the lazy dog again and again", "en", "a"),
    (2, "the quick brown fox jumps over the lazy dog again and again", "en", "b"),
    (3, None, None, None),
    (4, "", "en", "a"),
    (5, "x", "en", "a"),
    (6, LONG, "en", "a"),
    (7, LONG, "en", "c"),
    (None, "a row without an id", "en", "a"),
    (None, None, "en", None),
    (9, "é ü 漢字 😀 \t\n tab\u00a0space", "xx", "b"),
    (9, "é ü 漢字 😀 \t\n tab\u00a0space", "xx", "b"),
    (10, "same id, one text", "en", "b"),
    (10, "same id, another text", "en", "b"),
    (11, "0" * 5000, "en", "d"),
]


def awkward(spark):
    return spark.createDataFrame([(*r, 0, *EXTRA) for r in ROWS], CLASHING)


def empty(spark):
    return spark.createDataFrame([], CLASHING)


def texts():
    """doc_id and text as operators see them: null texts are empty."""
    return [(r[0], r[1] or "") for r in ROWS]
