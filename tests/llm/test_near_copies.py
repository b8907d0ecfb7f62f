import corpus_pipeline as P

from dynreach.llm import minmax_dedup as M

from tests.llm.test_minmax import plain_set


def pairs_between(n=300):
    """Pairs (2k, 2k + 1) that differ in two words of a hundred: 86 of 106 shingles are common."""
    rows = []
    for k in range(n):
        words = [f"a{k}x{i}" for i in range(100)]
        rows.append((2 * k, " ".join(words)))
        words[30], words[60] = "other", "another"
        rows.append((2 * k + 1, " ".join(words)))
    return rows


def test_the_stage_links_from_80_percent_on(spark):
    rows = pairs_between()
    a, b = plain_set(rows[0][1]), plain_set(rows[1][1])
    assert 80 <= 100 * len(a & b) / len(a | b) < 85
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    assert sorted(r.doc_id for r in P.one_of_each(spark, docs, "").collect()) == list(range(0, 600, 2))
    assert M.keep_one(docs).count() == 600  # op8's own threshold


def test_bands_hold_at_the_threshold():
    assert (M.band_rows(85), M.band_rows(80)) == (8, 6)
    for percent in (50, 70, 80, 85, 90):
        r = M.band_rows(percent)
        assert (1 - (percent / 100) ** r) ** (256 // r) <= 1e-4


def kept_at(rows, percent):
    sets = {d: plain_set(t) for d, t in rows}
    ids, parent = sorted(sets), {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {d for d in ids if find(d) == d}


def test_the_stage_on_given_documents(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    got = [r.doc_id for r in P.one_of_each(spark, docs, sf_dir).collect()]
    assert set(got) == kept_at(rows, 80) != kept_at(rows, 85) and len(got) == len(set(got))


def test_repeated_rows_leave_one(spark):
    long = " ".join(f"w{i}" for i in range(50))
    rows = [(1, long, "a"), (1, long, "a"), (1, long, "b"), (2, long + " x", "a"), (3, "other", "a"), (3, "text", "a"), (3, "text", "a"), (4, " \n", "a"), (4, " \n", "a"), (5, None, "a"), (5, None, "a"), (None, "one two", "a"), (None, "one two", "a")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)
    got = sorted(map(tuple, P.one_of_each(spark, docs, "").collect()), key=repr)
    assert got == sorted([rows[0], *rows[4:6], *rows[7:]], key=repr)
