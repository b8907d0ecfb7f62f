import zlib
from collections import Counter

import corpus_pipeline as P

from dynreach.llm import prefix_tokens, secret_scan

from tests.llm.test_minmax import brute
from tests.llm.test_tokens_secrets_shards import brute_spans, ids, odd, tokenizer  # noqa: F401


def redacted(text):
    at, out = 0, ""
    for s, _, _, e in brute_spans(text):
        if s >= at:
            out += text[at:s] + "[secret]"
        at = max(at, e)
    return out + text[at:]


def test_stages_against_brute_force(spark, sf_dir, tokenizer):  # noqa: F811
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    names = [n for n, _ in P.STAGES]
    assert names == ["language_id", "minmax_dedup", "secret_scan", "mixing", "packing"] and P.ORACLE_SQL is None
    now = {r.doc_id: r for r in docs.collect()}
    frame = docs
    for name, stage in P.STAGES[:-1]:
        frame = stage(spark, frame, sf_dir)
        assert frame.columns == docs.columns and frame.schema == docs.schema
        frame = spark.createDataFrame(frame.collect(), docs.schema)
        got = frame.collect()
        if name == "language_id":
            assert {r.doc_id for r in got} == set(now)  # all are clean
        if name == "minmax_dedup":
            want = {d for d, (_, c) in brute([(r.doc_id, r.text) for r in now.values()], 80).items() if d == c}
            assert {r.doc_id for r in got} == want and len(got) == len(want)
        if name == "secret_scan":
            assert all(r.text == redacted(now[r.doc_id].text) and r.n_chars == len(r.text) for r in got)
        if name == "mixing":
            copies = Counter(r.doc_id for r in got)
            assert set(copies) == set(now) and max(copies.values()) <= 3
        else:
            now = {r.doc_id: r for r in got}
    texts = {r.doc_id: [*ids(tokenizer, r.text), 2] for r in got}
    rows = P.STAGES[-1][1](spark, frame, sf_dir).collect()
    assert sum(r.length for r in rows) == sum(len(texts[d]) * n for d, n in copies.items())
    assert len({(r.row_id, r.piece) for r in rows}) == len(rows) and len({r.row_id for r in rows}) == sum(copies.values())
    for r in rows:
        part = texts[r.doc_id][r.start : r.start + r.length]
        assert b"".join(i.to_bytes(4, "little") for i in part) == r.ids and zlib.crc32(r.ids) == r.ids_crc32
    whole = P.run(spark, sf_dir).select("doc_id", "piece", "start", "length", "ids_crc32").collect()
    assert Counter(map(tuple, whole)) == Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows)


def test_near_copies_between_80_and_85_go(spark):
    words = [f"w{i}" for i in range(204)]  # 200 shingles; a changed word takes five of them

    def changed(n):
        return " ".join(f"new{i}" if i % 40 == 20 and i // 40 < n else w for i, w in enumerate(words))

    rows = [(1, " ".join(words), "en", "a", 1), (2, changed(4), "en", "a", 1), (3, " ".join(w[::-1] + "q" for w in words), "en", "a", 1)]
    assert brute([r[:2] for r in rows], 80)[2][1] == 1 and brute([r[:2] for r in rows], 85)[2][1] == 2
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r.doc_id for r in P.one_of_each(spark, docs, "").collect()) == [1, 3]


def test_odd_rows_pass_through(spark, odd):  # noqa: F811
    frame = odd
    for name, stage in P.STAGES[:-1]:
        frame = stage(spark, frame, "")
        assert frame.columns == odd.columns
    assert {r.doc_id for r in frame.collect()} == {3, 5, None}  # a null id links with nothing and stays
    for name, stage in P.STAGES:
        assert stage(spark, odd.limit(0), "").count() == 0
    assert prefix_tokens.default_tokenizer() and secret_scan.BASE_RULES
