import zlib
from collections import Counter, defaultdict

import numpy as np
from tokenizers import Tokenizer

from lwgraph.llm import mixing, packing

TEXTS = [
    "Plain words, it's here.", "", None, "Ünï çafé 12 ½ <|endoftext|> tail", "ΣΑΣ naïve é", "a" * 5000, "don't!!' 's ...'re", "x y " * 3000, "İstanbul ǅ", "\x00\t weird​"]


def test_word_cache_equals_tokenizer():
    whole = Tokenizer.from_file(packing.vocabulary())
    cache = packing.WordCache(packing.vocabulary())
    texts = [t or "" for t in TEXTS]
    for t, got in zip(texts, cache.encode(texts), strict=True):
        assert got.tolist() == whole.encode(t, add_special_tokens=False).ids, t


def test_word_cache_on_given_texts(spark):
    whole = Tokenizer.from_file(packing.vocabulary())
    texts = [r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()]
    cache = packing.WordCache(packing.vocabulary(), limit=500)
    for t, got in zip(texts, cache.encode(texts), strict=True):
        assert got.tolist() == whole.encode(t, add_special_tokens=False).ids


def test_hilbert_neighbours_are_adjacent():
    grid = np.stack(np.meshgrid(*[np.arange(8)] * 3), -1).reshape(-1, 3)
    keys = packing.hilbert_index(grid, 3)
    assert sorted(keys.tolist()) == list(range(512))
    walk = grid[np.argsort(keys)]
    assert (np.abs(np.diff(walk, axis=0)).sum(1) == 1).all()


def test_pieces_cover_every_id_once(spark):
    rows = [(i, t, "extra") for i, t in enumerate(TEXTS)] + [(3, "again", "extra"), (None, "no id", "extra")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, start string")
    out = packing.pack(docs, packing.vocabulary(), with_ids=True).collect()
    whole = Tokenizer.from_file(packing.vocabulary())
    sequences = defaultdict(list)
    for p in out:
        assert zlib.crc32(p.ids) == p.ids_crc32 and len(p.ids) == 4 * p.length
        sequences[p.sequence_id].append((p.offset, p.length))
    for parts in sequences.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at == 2048 or at & (at - 1) == 0
    assert sorted(sequences) == list(range(len(sequences)))
    for i, t in enumerate(TEXTS):
        if i == 3:
            continue
        parts = sorted((p.start, p.ids) for p in out if p.doc_id == i)
        ids = np.frombuffer(b"".join(x for _, x in parts), "<u4").tolist()
        assert ids == [*whole.encode(t or "", add_special_tokens=False).ids, 1]
    assert packing.pack(docs.limit(0), packing.vocabulary()).count() == 0


def test_mixing_against_direct_simulation(spark):
    sizes = {"a": 401, "b": 130, "c": 64, None: 9}
    rows = [(1000 * k + j, s) for k, (s, n) in enumerate(sizes.items()) for j in range(n)]
    docs = spark.createDataFrame(rows, "doc_id long, source string")
    weights = {"a": 5, "b": 3, "c": 2, None: 1}
    out = mixing.positions(docs, weights, block=4, period=11, cell_rows=50).collect()
    assert sorted(r.position for r in out) == list(range(len(rows)))
    by_slot = {}
    for r in out:
        assert by_slot.setdefault(r.slot, (r.source, r.block)) == (r.source, r.block)
    assert sorted(by_slot) == list(range(len(by_slot)))
    # less than one block from the exact share while all sources last
    plan = mixing.phases({s: -(-n // 4) for s, n in sizes.items()}, weights, 11)
    seen = Counter()
    for t in range(plan[0]["length"]):
        seen[by_slot[t][0]] += 1
        for s, w in weights.items():
            assert abs(seen[s] - (t + 1) * w / 11) < 1
    last = defaultdict(lambda: -1)
    for t in range(len(by_slot)):
        s, b = by_slot[t]
        assert b == last[s] + 1
        last[s] = b


def test_mix_keeps_rows_and_columns(spark):
    docs = spark.createDataFrame([(i, f"t{i}", "s", i) for i in range(300)] + [(5, "t5", "s", 5)], "doc_id long, text string, source string, position int")
    out = mixing.mix(docs)
    assert out.columns == docs.columns and sorted(out.collect()) == sorted(docs.collect())
    assert mixing.mix(docs.limit(0)).count() == 0


def test_pipeline_sequences_follow_the_mix(spark, monkeypatch):
    """The order of stage 4 reaches run()'s rows: stretch after stretch, and other weights give other sequences."""
    import corpus_pipeline

    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    sources = sorted(r.source for r in docs.select("source").distinct().collect())

    def packed(weights):
        mix = [("mixing", lambda s, rows, _: mixing.mix(rows, weights, block=8))] if weights else []
        monkeypatch.setattr(corpus_pipeline, "STAGES", [*mix, ("packing", corpus_pipeline.pack_sequences)])
        return sorted((r.sequence_id, r.offset, r.doc_id, r.start) for r in corpus_pipeline.run(spark, d).collect())

    monkeypatch.setattr(corpus_pipeline, "STRETCH", 16)
    one, other = ({s: 9 if s == most else 1 for s in sources} for most in (sources[0], sources[-1]))
    got = packed(one)
    where = {r.doc_id: r.position // 16 for r in mixing.positions(docs.select("doc_id", "source"), one, block=8).collect()}
    met = [where[i] for _, _, i, start in got if start == 0]
    assert met == sorted(met) and len(met) == docs.count() and max(met) > 5
    assert packed(other) != got and packed(None) != got


def test_stretches_count_along_files_and_partitions(spark, tmp_path):
    rows = spark.range(100).repartitionByRange(3, "id").sortWithinPartitions("id")
    assert all(r.stretch == r.id // 7 for r in mixing.stretches(rows, 7).collect())
    uneven = spark.range(100).selectExpr("id", "case when id < 2 then 0 when id < 10 then 1 else 2 end as p").repartitionById(3, "p").sortWithinPartitions("id")
    uneven.select("id").write.parquet(f"{tmp_path}/t")
    for read in (spark.read.parquet(f"{tmp_path}/t"), spark.read.parquet(f"{tmp_path}/t").select("id")):
        assert all(r.stretch == r.id // 7 for r in mixing.stretches(read, 7).collect())
    assert mixing.stretches(spark.range(0), 7).count() == 0


def test_every_character_is_cut_as_the_tokenizer_cuts_it():
    cache = packing.WordCache(packing.vocabulary())
    points = [*range(0x3400), *range(0xA000, 0xD800), *range(0xF900, 0x10000), *range(0x1E000, 0x20000)]
    texts = [f"ab{chr(c)}cd 's{chr(c)}{chr(c)}. x {chr(c)}1_" for c in points]
    want = cache.tokenizer.encode_batch_fast(texts, add_special_tokens=False)
    assert [c for c, got, made in zip(points, cache.encode(texts), want, strict=True) if got.tolist() != made.ids] == []
