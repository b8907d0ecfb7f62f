import hashlib
import random
import re
import zlib
from collections import Counter

import pytest

from dynreach.llm import packing, prefix_tokens, secret_scan, sharding

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [(1, None, None, None, None), (2, "", "en", "a", 0), (2, "", "en", "a", 0), (3, "x" * 5000 + " y" * 5000, "en", "a", 9), (None, "word", "en", None, 4), (5, "tie", "en", "a", 3), (6, "tie", "en", "a", 3)]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(*r, 1, 2) for r in ODD], DOCS + ", n_tokens int, shard int")


@pytest.fixture(scope="module")
def tokenizer():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(prefix_tokens.default_tokenizer()[0])


def ids(tokenizer, text):
    return tokenizer.encode(text or "", add_special_tokens=False).ids


def random_texts(n, seed=3):
    rng = random.Random(seed)
    parts = [*"ab  \n\t'sstllrevmd1²é.!x- 　漢字\x1c\x85", "<|endoftext|>", "ing", "'ll", " 're"]
    return ["".join(rng.choices(parts, k=rng.randint(0, 30))) for _ in range(n)]


def test_counts_and_prefixes(tokenizer):
    counter = prefix_tokens.PrefixCounter(*prefix_tokens.default_tokenizer())
    texts = random_texts(1500)
    assert counter.counts(texts) == [len(ids(tokenizer, t)) for t in texts]
    for t in texts[:200]:
        assert counter.prefixes(t) == [len(ids(tokenizer, t[:k])) for k in range(len(t) + 1)]
    long = "a" * 3000 + " b" * 500
    assert counter.prefixes(long)[-1] == len(ids(tokenizer, long))
    cut = counter.longest_prefix(long, 100)
    assert len(ids(tokenizer, long[:cut])) <= 100 < len(ids(tokenizer, long[: cut + 1]))
    assert counter.first_over("", 0) == -1 and counter.first_over("a b", 1) == 2


def test_token_counts_query(spark, sf_dir, odd, tokenizer):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for frame in (docs, odd, odd.limit(0)):
        want = Counter((r.doc_id, len((r.text or "").encode()), n := len(ids(tokenizer, r.text)), n > 512) for r in frame.collect())
        assert Counter(map(tuple, prefix_tokens.token_counts(frame).collect())) == want
    got = {r.doc_id: r.counts for r in prefix_tokens.prefix_counts(odd.where("doc_id = 5")).collect()}
    assert got[5] == [len(ids(tokenizer, "tie"[:k])) for k in range(4)]


def test_packing(spark, sf_dir, odd, tokenizer):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for frame in (docs, odd, odd.limit(0)):
        rows = packing.pack(frame, with_ids=True).collect()
        texts = Counter((r.doc_id, tuple([*ids(tokenizer, r.text), 2])) for r in frame.collect())
        got, open_ids = Counter(), {}
        for r in rows:
            assert r.ids_crc32 == zlib.crc32(r.ids) and len(r.ids) == 4 * r.length <= 4096
        for r in sorted(rows, key=lambda r: (r.doc_id or -1, r.sequence_id, r.offset)):
            open_ids.setdefault(r.doc_id, []).append(r)
        flat = Counter()
        for r in rows:
            flat[r.doc_id] += r.length
        want = Counter()
        for (d, x), n in texts.items():
            want[d] += n * len(x)
        assert flat == want
        unique = {d for d, n in Counter(d for d, _ in texts.elements()).items() if n == 1}
        for d in unique:
            pieces = sorted(open_ids[d], key=lambda r: r.piece)
            data = b"".join(p.ids for p in pieces)
            assert tuple(int.from_bytes(data[k : k + 4], "little") for k in range(0, len(data), 4)) == next(x for e, x in texts if e == d)
            assert [p.start for p in pieces] == [sum(q.length for q in pieces[:k]) for k in range(len(pieces))]
            assert all(p.length == 1024 for p in pieces[1:])
        by_sequence = {}
        for r in rows:
            by_sequence.setdefault(r.sequence_id, []).append((r.offset, r.length))
        for parts in by_sequence.values():
            at = 0
            for offset, length in sorted(parts):
                assert offset == at
                at += length
            assert at <= 1024


def test_encoder_keeps_to_its_bytes(tokenizer):
    encoder = packing.Encoder(prefix_tokens.default_tokenizer()[0], cache_bytes=20_000)
    texts = [" ".join(f"w{i}é{i % 7}" for i in range(k, k + 60)) for k in range(0, 600, 20)] + random_texts(40)
    for k in range(0, len(texts), 5):
        got = [b for b in encoder.encode(texts[k : k + 5])]
        assert got == [b"".join(i.to_bytes(4, "little") for i in ids(tokenizer, t)) for t in texts[k : k + 5]]
        assert 0 <= encoder.held <= 20_000
        assert encoder.held == sum(encoder.taken(u, x) for kept in encoder.kept.values() for u, x in kept.items())
    assert packing._encoder(prefix_tokens.default_tokenizer()[0], 1) is not packing._encoder(prefix_tokens.default_tokenizer()[0], 2)


def test_rows_and_ids_of_pieces(spark, odd, tokenizer, monkeypatch):
    monkeypatch.setattr(packing, "FLUSH_PIECES", 3)
    rows = packing.pack(odd, with_ids=True, with_row=True, shared=True).collect()
    assert len({(r.row_id, r.piece) for r in rows}) == len(rows) and len({r.row_id for r in rows}) == odd.count()
    flat = Counter()
    for r in rows:
        flat[r.row_id] += r.length
    assert Counter(flat.values()) == Counter(len(ids(tokenizer, r.text)) + 1 for r in odd.collect())


def test_open_bins_close_the_fullest():
    bins = packing.OpenBins(10, 2)
    assert [bins.place(n) for n in (6, 7, 8)] == [(0, 0), (1, 0), (2, 0)]
    assert bins.open == 2 and bins.place(2) == (1, 7)  # bin 2, the fullest, has closed
    assert bins.place(4) == (0, 6)


def brute_spans(text):
    text, out = text or "", []
    for order, r in enumerate(secret_scan.BASE_RULES + secret_scan.MORE_RULES):
        for m in re.finditer(r.pattern, text, re.ASCII):
            if len(m.group(r.group)) >= r.least:
                out.append((m.start(), order, r.kind, m.end()))
    return sorted(out)


def test_trigram_queries():
    assert secret_scan.trigram_query(r"AKIA[A-Z0-9]+") == [frozenset({"aki", "kia"})]
    assert secret_scan.trigram_query("[0-9a-f]+") is None
    assert secret_scan.trigram_query("ab|cdef") is None
    assert secret_scan.trigram_query("(abc)?x.*defg") == [frozenset({"def", "efg"})]
    clauses = secret_scan.trigram_query(secret_scan.BASE_RULES[0].pattern)
    for text in ("password", "passwd", "secret", "token", "apikey", "api_key"):
        assert any(c <= {text[i : i + 3] for i in range(len(text) - 2)} for c in clauses)


def test_secret_scan(spark, sf_dir, odd):
    rng = random.Random(5)
    parts = ["password", "API_KEY", "apikey", "ToKen", '"', "'", " ", "  ", ":", "=", "abcdef", "Zz/9+=", "AKIA", "AKIA" + "A1" * 9, "0a" * 13, "é", "😀", "\n", "ghp_" + "a1B" * 13, "-----BEGIN RSA PRIVATE KEY-----", "ſecret", "toKen"]
    made = [(i, "".join(rng.choices(parts, k=rng.randint(0, 14)))) for i in range(1500)]
    frames = [spark.createDataFrame(made, "doc_id long, text string"), odd, odd.limit(0), spark.read.parquet(f"{sf_dir}/documents.parquet")]
    for frame in frames:
        got = Counter((r.doc_id, r.n_assign, r.n_access, r.n_hex, r.base_sha256, r.spans) for r in secret_scan.digest(frame).collect())
        want = Counter()
        for r in frame.collect():
            found = brute_spans(r.text)
            say = lambda xs: ",".join(f"{k}:{s}:{e}" for s, _, k, e in xs)
            base = [x for x in found if x[1] < 3]
            n = Counter(x[2] for x in base)
            want[(r.doc_id, n["assign"], n["access"], n["hex"], hashlib.sha256(say(base).encode()).hexdigest(), say(found))] += 1
        assert got == want
    assert sum(r.n_assign + r.n_access + r.n_hex for r in secret_scan.digest(frames[0]).collect()) > 0
    clean = secret_scan.redact(frames[0])
    for r, (_, text) in zip(clean.orderBy("doc_id").collect(), made):
        merged, at, out = brute_spans(text), 0, ""
        for s, _, _, e in merged:
            if s >= at:
                out += text[at:s] + "[secret]"
            at = max(at, e)
        assert r.text == out + text[at:]


@pytest.mark.parametrize("law", sharding.LAWS)
def test_shards(spark, sf_dir, odd, law):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for frame in (docs, odd, odd.limit(0)):
        rows = sharding.assign_shards(frame, law=law, bucket_bytes=30_000).collect()
        want = Counter((r.doc_id, len((r.text or "").encode()) + 1, zlib.crc32((r.text or "").encode())) for r in frame.collect())
        assert Counter((r.doc_id, r.size, r.text_crc32) for r in rows) == want
        by = {s: [r for r in rows if r.shard == s] for s in range(8)}
        for part in by.values():
            assert sorted(r.slot for r in part) == list(range(len(part)))
        if law == "rows":
            assert max(map(len, by.values())) - min(map(len, by.values())) <= 1
        if law == "bytes" and rows:
            sums = [sum(r.size for r in p) for p in by.values()]
            assert max(sums) - min(sums) <= 2 * max(r.size for r in rows)
        if law == "key":
            assert all(r.grown_shard in (r.shard, 8) for r in rows)
            assert all(len({(r.shard, r.grown_shard) for r in rows if r.doc_id == d}) == 1 for d in {r.doc_id for r in rows})
        else:
            assert all(r.grown_shard is None for r in rows)


def test_secrets_of_hot_texts_and_clashing_names(spark, monkeypatch):
    monkeypatch.setattr(secret_scan, "HOT_SHARE", 3)
    hot = "password = abcdefgh and " + "0a" * 13
    rows = [(i, hot, "mine", 5) for i in range(20)] + [(50 + i, "nothing here", None, 6) for i in range(20)] + [(90, None, "x", 7), (91, None, None, 8), (92, "token: zyxwvu", None, 9), (93, "", "y", 1)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, secret_spans string, __key int").repartition(3)
    clean = {r.doc_id: tuple(r)[1:] for r in secret_scan.redact(frame).collect()}
    assert len(clean) == len(rows) and secret_scan.redact(frame).columns == frame.columns
    for d, t, s, k in rows:
        want = {hot: "[secret] and [secret]", "token: zyxwvu": "[secret]"}.get(t, t)
        assert clean[d] == (want, s, k)
    assert {r.doc_id: r.spans for r in secret_scan.digest(frame).collect()} == {d: ",".join(f"{k}:{s}:{e}" for s, _, k, e in brute_spans(t)) for d, t, _, _ in rows}


def brute_places(rows, law, seed, buckets):
    """Both passes over (id, text, hash) rows in plain Python: id -> (shard, slot)."""
    dealt = {}
    for d, text, h in rows:
        dealt.setdefault((h >> 8) % buckets, []).append((h, d, len(text.encode()) + 1))
    line = []
    for b in sorted(dealt):
        group = sorted(dealt[b])
        line += [group[i] for i in sharding.fisher_yates(len(group), seed, b)]
    total, at, out, slots = sum(n for _, _, n in line), 0, {}, Counter()
    for position, (_, d, n) in enumerate(line):
        shard = {"rows": position % 8, "bytes": min(7, at * 8 // total), "key": sharding.jump_shard(sharding.key_of(d, seed), 8)}[law]
        out[d] = (shard, slots[shard])
        slots[shard] += 1
        at += n
    return out


@pytest.mark.parametrize("law", sharding.LAWS)
@pytest.mark.parametrize("stretch, most", [(4096, 100_000), (2, 0)])
def test_places_match_brute_force(spark, sf_dir, law, stretch, most, monkeypatch):
    from pyspark.sql import functions as F

    monkeypatch.setattr(sharding, "STRETCH", stretch)
    monkeypatch.setattr(sharding, "MOST_BROADCAST", most)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    hashed = docs.withColumn("h", F.xxhash64(F.lit(7), "doc_id", F.crc32("text"), F.monotonically_increasing_id()))
    buckets = sharding.bucket_count(docs, "text", 30_000)
    assert buckets > 4
    want = brute_places([tuple(r) for r in hashed.collect()], law, 7, buckets)
    got = sharding.assign_shards(docs, law=law, bucket_bytes=30_000).collect()
    assert {r.doc_id: (r.shard, r.slot) for r in got} == want


@pytest.mark.parametrize("law", sharding.LAWS)
def test_large_ids_beside_a_null_one(spark, law, tmp_path):
    rows = [(2**60 + 1, "a", 2**60 + 1), (2**60 + 3, "b", None), (None, "c", 2**61 + 1), (2**62 + 5, None, 1)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, n_chars long")
    got = sharding.assign_shards(frame, law=law).collect()
    assert Counter(r.doc_id for r in got) == Counter(r[0] for r in rows)
    if law == "key":
        assert {r.doc_id: r.shard for r in got} == {r[0]: sharding.jump_shard(sharding.key_of(r[0], 7), 8) for r in rows}
    sharding.write_shards(frame, str(tmp_path), law=law)
    assert Counter(map(tuple, spark.read.parquet(f"{tmp_path}/shards").select(*frame.columns).collect())) == Counter(rows)


def test_write_shards(spark, sf_dir, tmp_path):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    sharding.write_shards(docs, str(tmp_path), bucket_bytes=50_000)
    back = spark.read.parquet(f"{tmp_path}/shards")
    assert Counter(map(tuple, back.select(*docs.columns).collect())) == Counter(map(tuple, docs.collect()))
    order = [r.doc_id for r in back.orderBy("slot", "shard").collect()]
    assert order != sorted(order)
