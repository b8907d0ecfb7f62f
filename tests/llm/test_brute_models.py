"""Predictions of op2 and op3 against the same models walked through one text at a time, in plain Python."""

import math

import numpy as np
import pytest

from dynreach.llm import language_id, toxicity

from tests.llm.test_tokens_secrets_shards import odd  # noqa: F401

ODD_TEXTS = [None, "", "123 !!", "a", "É à", "YOU  you're\tYOUR!!!", "l33t sc4m b-c d'e aaa", "漢字 かな", "x" * 3000, "퟿ \U0001F600 ok?"]


def slow_language(model, text):
    low = (text or "").lower()
    if not any(c.isalpha() for c in low):
        return "und", 0.0
    codes, out = [0], True
    for c in low:  # a run without letters counts as one break
        if c.isalpha():
            codes.append(ord(c))
            out = False
        elif not out:
            codes.append(0)
            out = True
    codes += [0] if not out else []
    if low[0].isalpha() is False:
        codes.insert(1, 0)  # the first run is kept beside the mark of the beginning
    if not low[-1].isalpha():
        codes.append(0)
    wrap = lambda x: x & 0xFFFFFFFF
    a, b, c = (int(x) for x in language_id._MULTIPLIERS)
    bits = int(math.log2(language_id.WIDTH))
    counts = [0] * language_id.WIDTH
    for i, x in enumerate(codes):
        grams = [wrap(wrap(x * a) * c)] if x else []
        if i + 1 < len(codes):
            two = wrap((wrap(x * a) ^ wrap(codes[i + 1] * b)) * c)
            grams.append(two)
            if i + 2 < len(codes):
                grams.append(wrap((two ^ wrap(codes[i + 2] * a)) * b))
        for g in grams:
            counts[wrap((g ^ (g >> 15)) * a) >> (32 - bits)] += 1
    vector = [math.log1p(n) * float(w) for n, w in zip(counts, model.idf)]
    length = math.sqrt(sum(v * v for v in vector))
    cosines = [sum(v / length * float(w) for v, w in zip(vector, centre) if v) for centre in model.centroids]
    best = max(range(len(cosines)), key=cosines.__getitem__)
    return model.names[best], cosines[best]


def test_languages_against_one_by_one(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = language_id.learn(docs.where(~language_id.held_out()))
    texts = [r.text for r in docs.orderBy("doc_id").limit(25).collect()] + ODD_TEXTS
    for text, lang, score in zip(texts, *model.predict(texts)[:2]):
        want, cosine = slow_language(model, text)
        assert lang == want and score == pytest.approx(cosine, abs=1e-4)


def slow_features(text, lexicon):
    text = text or ""
    words = text.split()
    n, data = max(1, len(words)), text.encode("utf-8", "surrogatepass")
    chars = max(1, len(data))
    marks = "".join(chr(i) for i in range(33, 127) if not chr(i).isalnum())

    def term(low):
        best = low if low in lexicon.lift else None
        for k in toxicity.STEMS:
            stem = low[:k] + "*"
            if len(low) >= k and stem in lexicon.lift and lexicon.lift[stem] > (lexicon.lift[best] if best else 0.0):
                best = stem
        return best

    hits, you, shouted, hidden, stretched = [], [], 0, 0, 0
    for i, raw in enumerate(words):
        word = raw.strip(marks)
        low = word.lower()
        found = term(low)
        if any(not c.isalpha() for c in low) and any(c.isalpha() for c in low) and "'" not in low and "-" not in low:
            hidden += 1
            found = found or term("".join(c for c in low.translate(toxicity._STANDS_FOR) if c.isalpha()))
        stretched += low.isalpha() and any(low[j] == low[j + 1] == low[j + 2] for j in range(len(low) - 2))
        shouted += len(word) > 2 and word.isupper()
        if low in toxicity.SECOND_PERSON:
            you.append(i)
        if found:
            hits.append((i, found))
    lifts = [lexicon.lift[t] for _, t in hits]
    near = sum(any(abs(i - j) <= toxicity.NEAR for j in you) for i, _ in hits)
    of = lambda test: sum(map(test, data)) / chars
    return [
        math.log1p(len(words)), len(hits) / n, len({t for _, t in hits}), sum(lifts) / n, max(lifts, default=0.0), near / n, len(you) / n, of(lambda b: 65 <= b < 91),
        shouted / n, data.count(b"!") / n, data.count(b"?") / n, of(lambda b: b < 128 and chr(b) in marks), hidden / n, stretched / n, of(lambda b: 48 <= b < 58), len(hits),
    ]


def slow_score(model, text):
    x = slow_features(text, model.lexicon)
    raw = model.trees.base
    for tree in model.trees.trees:
        node, inner = 0, len(tree.feature)
        while node < inner:
            k = tree.feature[node]
            place = sum(edge < x[k] for edge in model.trees.edges[k])
            node = 2 * node + 1 + (place > tree.bin[node])
        raw += tree.leaf[node - inner]
    xs, ps = model.knots
    if raw <= xs[0]:
        fitted = ps[0]
    elif raw >= xs[-1]:
        fitted = ps[-1]
    else:
        i = next(i for i in range(len(xs) - 1) if xs[i] <= raw <= xs[i + 1])
        fitted = ps[i] + (ps[i + 1] - ps[i]) * (raw - xs[i]) / (xs[i + 1] - xs[i]) if xs[i + 1] > xs[i] else ps[i]
    return min(1.0, max(0.0, 0.999 * fitted + 0.001 / (1 + math.exp(-raw))))


def test_toxicity_against_one_by_one(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    model = toxicity.learn(docs, labels.where(~toxicity.held_out()))
    assert model.lexicon.lift and model.trees.trees
    toxic = labels.where("toxic = 1").select("doc_id").limit(15)
    texts = [r.text for r in docs.join(toxic, "doc_id", "left_semi").collect()] + [r.text for r in docs.orderBy("doc_id").limit(40).collect()] + ODD_TEXTS
    for text in texts:
        assert slow_features(text, model.lexicon) == pytest.approx(toxicity.features(text, model.lexicon), abs=1e-9)
    assert [slow_score(model, t) for t in texts] == pytest.approx(list(model.scores(texts)), abs=1e-9)
    assert np.ptp(model.scores(texts)) > 0.5
