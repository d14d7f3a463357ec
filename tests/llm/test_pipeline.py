"""The pipeline's stages against plain Python on the small documents."""

import duckdb

import corpus_pipeline as cp
from tidelabel.llm import line_dedup
from tidelabel.llm.common import documents, materialise


def test_stages(spark, sf_dir):
    docs = documents(spark, sf_dir)
    columns = docs.columns
    sizes = [docs.count()]
    for name, stage in cp.STAGES[:-1]:
        before, docs = docs, materialise(stage(spark, docs, sf_dir), f"test-{name}")
        assert docs.columns == columns
        sizes.append(docs.count())
        if name == "line_dedup":
            con = duckdb.connect()
            t = before.toArrow()
            con.register("documents", t)
            gone = {}
            for d, n, *_ in con.execute(line_dedup.ORACLE).fetchall():
                gone.setdefault(d, set()).add(n)
            want = {r.doc_id: "\n".join(x for i, x in enumerate(r.text.split("\n")) if i not in gone.get(r.doc_id, ())) for r in before.collect()}
            got = {r.doc_id: r.text for r in docs.collect()}
            assert got == {d: x for d, x in want.items() if d not in gone or x.strip()}
    assert sizes == sorted(sizes, reverse=True) and sizes[-1] > sizes[0] / 3
    packed = cp.STAGES[-1][1](spark, docs, sf_dir)
    assert packed.select("doc_id").distinct().count() == sizes[-1]


def test_dropped_documents_are_the_rejected_ones(spark, sf_dir):
    docs = documents(spark, sf_dir)
    from tidelabel.llm import toxicity

    scored = toxicity.score(docs, toxicity.train(docs, toxicity.training_labels(spark, sf_dir)))
    kept = {r.doc_id for r in cp.toxicity_stage(spark, docs, sf_dir).collect()}
    assert kept == {r.doc_id for r in scored.where("predicted = 0").collect()}


def test_classes_of_characters_take_little_memory():
    """Lists of all code points, made in each of a machine's workers at once, brought an executor above its limit."""
    import tracemalloc

    from tidelabel.llm import language

    language.classes.cache_clear()
    tracemalloc.start()
    word, letter = language.classes()
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 10_000_000
    for i in (*range(0x3000), *range(0xD7F0, 0xE010), *range(0x1F5F0, 0x1F610), 0x10FFFF):
        c = chr(i)
        assert word[i] == (bool(language.LETTERS.fullmatch(c)) and not 0xD800 <= i < 0xE000) and letter[i] == (c.isalpha() and not 0xD800 <= i < 0xE000)
