import random

import corpus_pipeline
from graphloop.llm import byte_bpe, mixing
from tests.llm.test_near_dup import brute_force

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def corpus():
    rng = random.Random(11)
    words = ["".join(rng.choice("abcdefghij") for _ in range(6)) for _ in range(900)]

    def prose(n):
        return " ".join(rng.choice(words) for _ in range(n))

    rows = []
    for k in range(60):
        text = prose(60) + "\n" + prose(30)
        if k % 3 == 0:
            text += "\nThis line is everywhere"
        if k % 10 == 9:
            text = rows[-1][1].replace(" ", " other ", 1)
        rows.append((k, text, "en", f"s{k % 4}", len(text)))
    rows.append((60, "#### |||| %%%% " * 20, "en", "s0", 300))
    rows += [(61, None, None, None, None), (62, "", "en", "s1", 0), (63, prose(5), "en", None, 40)]
    return rows


def test_pipeline_equals_a_plain_version(spark, tmp_path):
    rows = corpus()
    spark.createDataFrame(rows, DOCS).write.parquet(str(tmp_path / "documents.parquet"))
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    texts = {}
    for doc, text, *_ in rows:
        if doc < 60:
            texts[doc] = "\n".join(line for line in text.split("\n") if line != "This line is everywhere")
    groups = {doc: component for doc, _, component in brute_force(sorted(texts.items()), 5, 80)}
    texts = {doc: t for doc, t in texts.items() if groups[doc] == doc}
    assert len(texts) < 60
    assert {r.doc_id for r in got} <= set(texts)
    assert all(r.round_trip and r.n_tokens == len(r.ids) for r in got)
    left = spark.createDataFrame([(d, t, "en", f"s{d % 4}", len(t)) for d, t in texts.items()], DOCS)
    taken = {r.id: r.copies for r in mixing.mix(left).collect()}
    counts = {}
    for r in got:
        counts[r.doc_id] = counts.get(r.doc_id, 0) + 1
    assert counts == {d: n for d, n in taken.items() if n}
    vocabulary = byte_bpe.Vocabulary.load(corpus_pipeline.public_tokenizers.path(corpus_pipeline.VOCABULARY))
    assert all(vocabulary.decode(r.ids).tobytes().decode() == texts[r.doc_id] for r in got)


def test_stages_take_an_empty_table(spark, tmp_path):
    spark.createDataFrame([], DOCS).write.parquet(str(tmp_path / "documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_stage_columns(spark):
    docs = spark.createDataFrame(corpus(), DOCS)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, "").columns == corpus_pipeline.COLUMNS
