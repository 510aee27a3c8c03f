import math
from collections import Counter

from ptree_rules.llm.language_id import BUCKETS, LENGTHS, SMOOTHING, fit, identified, op3_language_id


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    truth = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang")
    got = op3_language_id(spark, sf).join(truth, "doc_id").where("held_out and lang_pred != 'und'").collect()
    assert len(got) > 150
    assert sum(r.lang == r.lang_pred for r in got) / len(got) > 0.98
    assert all(0 <= r.score <= 1 for r in got)


def test_texts_without_letters_are_und(hard, none):
    model = fit(hard)
    got = {r.doc_id: r for r in identified(hard.select("doc_id", "text"), model).collect()}
    assert {i for i, r in got.items() if r.lang_pred == "und"} == {1, 2, 3, 9, 10}
    assert got[10].score == 0 and got[11].lang_pred == "fr"
    assert identified(none.select("doc_id", "text"), model).count() == 0


def test_text_alone(hard):
    got = identified(hard.select("text"), fit(hard))
    assert got.columns == ["text", "lang_pred", "score"] and got.count() == hard.count()


def test_nothing_learned(hard, none):
    got = identified(hard.select("doc_id", "text"), fit(none)).collect()
    assert len(got) == hard.count() and {(r.lang_pred, r.score) for r in got} == {("und", 0.0)}


def test_fit_reads_a_bounded_sample(hard):
    assert len(fit(hard, fit_rows=1)[0]) <= 4


def test_scores_equal_a_slow_naive_bayes(spark):
    """Counts in dicts and Python floats, over the same hashed n-grams made one character at a time."""
    rows = [(i, t, lang) for i, (t, lang) in enumerate([("the cat sat on the mat", "en"), ("le chat est assis", "fr"), ("die Katze sitzt hier", "de"), ("the dog ran", "en"), ("un chien court vite", "fr"), ("ü ö ä straße", "de")] * 3)]
    asked = ["the chat", "Straße und Katze", "vite vite", "x", "12 a", "the cat sat on the mat " * 50]
    mix = lambda h: ((h ^ (h >> 15)) & 0xFFFFFFFF)

    def grams(text):
        padded = f" {text.lower()} "
        for n in LENGTHS:
            for at in range(len(padded) - n + 1):
                h = n
                for c in padded[at : at + n]:
                    h = mix(((h ^ ord(c)) * 0x9E3779B1) & 0xFFFFFFFF)
                yield h % BUCKETS

    counts, docs = {}, Counter(lang for *_, lang in rows)
    for _, t, lang in rows:
        counts.setdefault(lang, Counter()).update(grams(t))
    total = {x: sum(c.values()) for x, c in counts.items()}

    def told(text):
        score = {x: math.log(docs[x] / len(rows)) + sum(math.log((counts[x][g] + SMOOTHING) / (total[x] + SMOOTHING * BUCKETS)) for g in grams(text)) for x in counts}
        best = max(sorted(score), key=score.get)
        return best, 1 / sum(math.exp(s - score[best]) for s in score.values())

    model = fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    got = identified(spark.createDataFrame([(t, 7.0, "mine") for t in asked], "text string, score double, r string"), model)
    assert got.columns == ["text", "r", "lang_pred", "score"]
    for r in got.collect():
        want = told(r.text)
        assert r.lang_pred == want[0] and abs(r.score - want[1]) < 1e-3 and r.r == "mine"
