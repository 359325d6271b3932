"""Misspelled terms after training."""

import random

from warpspan.llm import toxicity


def test_trained_lexicon_takes_misspellings(spark, make_docs):
    rng = random.Random(9)
    plain = [f"w{k}" for k in range(200)]
    terms = ["trash", "idiot", "worthless", "zorgish", "zorgly"]
    texts = []
    for i in range(400):
        words = [rng.choice(plain) for _ in range(40)]
        if i % 4 == 0:
            words[5:5] = rng.sample(terms, 3)
        texts.append(" ".join(words))
    labels = spark.createDataFrame([(i, 1, int(i % 4 == 1)) for i in range(1, 401)], "doc_id bigint, quality int, toxic int")
    model = toxicity.fit(make_docs(texts), labels)
    assert any(e.stem and "trash".startswith(e.text) for e in model.entries)
    memo = toxicity._Memo(toxicity.LexiconAutomaton(model.entries))
    for word in ("idjot", "trqsh", "wortless", "zqrgish", "ztrash", "xdiot", "diot", "pathetc", "stupyd"):
        assert memo[word] is not None and memo[word][1] == 1, word
    assert memo["w17"] is None and memo["trash"][1] == 0
    scores = [r.s for r in make_docs(["a b c d", "you are an idjot and trqsh"], parts=1).orderBy("doc_id").select(toxicity.score("text", model).alias("s")).collect()]
    assert scores[1] > scores[0]
