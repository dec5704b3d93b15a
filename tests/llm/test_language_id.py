import random

from graphloop.llm import language_id

PARTS = {"en": ["the", "ing", "th", "and", "wh"], "de": ["sch", "ung", "ein", "ö", "ver"], "fr": ["eau", "é", "que", "ment"], "es": ["ción", "ñ", "ado", "ue"]}


def corpus(n):
    rng = random.Random(8)
    rows = []
    for k in range(n):
        lang = sorted(PARTS)[k % 4]
        rows.append((k, " ".join("".join(rng.choice(PARTS[lang]) for _ in range(rng.randrange(1, 4))) for _ in range(rng.randrange(4, 40))), lang))
    return rows


def test_held_out_accuracy_and_odd_rows(spark):
    rows = corpus(400) + [(1000, None, "en"), (1001, "", "en"), (1002, "12 !! 34", "de"), (None, "the and", "en"), (1003, "the thing and", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    found = {r.doc_id: r for r in language_id.digest(df).collect()}
    assert len(found) == len(rows)
    held = [(k, lang) for k, _, lang in rows[:400] if found[k].held_out]
    assert 100 < len(held) < 170
    assert sum(found[k].lang_pred == lang for k, lang in held) / len(held) > 0.97
    assert all(0 <= r.score <= 1 for r in found.values())
    assert {found[k].lang_pred for k in (1000, 1001, 1002)} == {"und"}
    assert found[1003].lang_pred == "en"
    assert not found[None].held_out


def test_one_language_and_none(spark):
    df = spark.createDataFrame([(k, f"the and {k}", "en") for k in range(20)], "doc_id long, text string, lang string")
    assert {r.lang_pred for r in language_id.digest(df).collect()} == {"en"}
    assert {r.lang_pred for r in language_id.digest(df.withColumn("lang", df.lang.substr(9, 1)).where("false")).collect()} == set()
    assert {r.lang_pred for r in language_id.identify(df, None).collect()} == {"und"}
