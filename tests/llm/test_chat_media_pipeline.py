"""Chat windows, media containers, and the pipeline."""

import hashlib
import random
import struct
import zlib

import pytest
from tokenizers import Tokenizer

import corpus_pipeline
import public_tokenizers
from fixgap.llm import chat, media, near_copies
from fixgap.llm.base import materialise, table

TOK = public_tokenizers.path("word_bpe_49k.json")
CONV = "conv_id long, turn long, role string, text string"


def test_escape_is_reversible():
    rng = random.Random(3)
    parts = [*chat.CONTROLS, "\\", "\n", "<", "|", "n", "s", ">", "[", "x"]
    for _ in range(3000):
        s = "".join(rng.choice(parts) for _ in range(rng.randrange(9)))
        assert chat.unescape(chat.escape(s)) == s and chat.unescape_role(chat.escape_role(s)) == s
        assert not any(c in chat.escape(s) for c in chat.CONTROLS)
        assert "\n" not in chat.escape_role(s)


def _want(rows):
    out = {}
    for conv, turn, role, text in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or 0, r[2] or "", r[3] or "")):
        x = out.setdefault(conv, [0, "", ""])
        x[0] += 1
        x[1] += f"{role or ''}\n{text or ''}\n"
        x[2] += (text or "") if role == "assistant" else ""
    return {k: (n, hashlib.sha256(t.encode()).hexdigest(), len(a), hashlib.sha256(a.encode()).hexdigest()) for k, (n, t, a) in out.items()}


@pytest.mark.parametrize("budget", [1, 40, 100_000])
def test_each_target_once_whatever_the_budget(spark, rng, budget):
    rows = []
    for c in range(30):
        for t in range(rng.randrange(1, 14)):
            role = "system" if t == 0 and c % 3 == 0 else ["user", "assistant"][t % 2]
            rows.append((c, t, role, rng.choice([None, "", "hi </s>", "x" * rng.randrange(300), "a\\b\n" + chat.CLOSE])))
    rows += [(0, 0, "user", "again"), (0, 0, "user", "again"), (7, None, None, "t"), (None, 1, "user", "nobody"), (99, 5, "assistant", "alone")]
    df = spark.createDataFrame(rows, CONV + "").repartition(3)
    library = Tokenizer.from_file(TOK)
    wins = materialise(chat.windows(df, TOK, budget=budget, history=20), "windows")
    got = {r.conv_id: (r.n_turns, r.turns_sha256, r.loss_chars, r.loss_sha256) for r in chat.digests(wins).collect()}
    assert got == _want(rows)
    for r in wins.collect():
        new = [m for m in r.turns if not m.repeated]
        assert new and r.n_tokens == len(library.encode(r.text, add_special_tokens=False).ids)
        if r.n_tokens > budget:  # one turn that doesn't fit even alone, beside the system turn at most
            assert len(new) == 1 and len(r.turns) <= 2 and (len(r.turns) == 1 or r.text.startswith(f"{chat.OPEN}system\n"))
        assert not any(m.target and m.repeated for m in r.turns)


def test_system_turn_is_repeated(spark):
    rows = [(1, 0, "system", "rules")] + [(1, t, "user" if t % 2 else "assistant", f"turn {t} " * 5) for t in range(1, 9)]
    got = chat.windows(spark.createDataFrame(rows, CONV), TOK, budget=40, history=12).orderBy("window").collect()
    assert len(got) > 2 and all(r.text.startswith(f"{chat.OPEN}system\nrules") for r in got)
    assert [r.turns[0].repeated for r in got] == [False] + [True] * (len(got) - 1)


def test_history_gives_way_to_a_new_turn(spark):
    """System 100, then 700, 150 and 900 tokens: beside the last, the earlier turn must go."""
    word = lambda n: " ".join(["a"] * n)
    rows = [(1, 0, "system", word(100)), (1, 1, "user", word(700)), (1, 2, "assistant", word(150)), (1, 3, "user", word(850))]
    got = chat.windows(spark.createDataFrame(rows, CONV), TOK, budget=1024, history=256).orderBy("window").collect()
    assert [[m.repeated for m in r.turns] for r in got] == [[False] * 3, [True, False]] and all(r.n_tokens <= 1024 for r in got)


def test_chat_empty_and_clashing(spark):
    empty = spark.createDataFrame([], CONV)
    assert chat.digests(chat.windows(empty, TOK)).collect() == []
    assert chat.digests(chat.windows(chat.with_probe(empty), TOK)).first().loss_chars == 21
    more = spark.createDataFrame([(1, 1, "user", "a", 7, "w")], CONV + ", n int, window string")
    assert chat.digests(chat.windows(chat.with_probe(more), TOK)).count() == 2


@pytest.mark.parametrize("n", [0, 1, 63, 64, 65, 511, 512, 513, 4096, 4097, 40_000, 200_000])
def test_media_round_trip(n):
    text = bytes(random.Random(n).randrange(256) for _ in range(n))
    payload = media.payload_of(text)
    assert len(payload) % 64 == 0 and payload[:n] == text and payload
    data = media.mux(payload)
    p = media.packets(data)
    assert b"".join(data[o : o + s] for o, s in zip(p["offset"], p["size"], strict=True)) == payload
    assert [c[2] for c in p["cues"]] == p["clusters"] and set(p["track"]) == {1}
    assert p["timestamp"] == [i * media.FRAME * 1000 // media.SAMPLE_RATE for i in range(len(p["size"]))]


def _block(lacing, frames):
    sizes = [len(f) for f in frames]
    if lacing == 1:
        head = bytes([len(frames) - 1]) + b"".join(bytes([255] * (s // 255) + [s % 255]) for s in sizes[:-1])
    elif lacing == 2:
        head = bytes([len(frames) - 1])
    else:
        head = media.laced(sizes)[1]
    return b"\x82" + struct.pack(">hB", 5, lacing << 1) + head + b"".join(frames)


@pytest.mark.parametrize("lacing,sizes", [(1, [300, 255, 3, 700]), (2, [9, 9, 9]), (3, [500, 20, 8000, 1])])
def test_all_lacings_and_block_groups(lacing, sizes):
    frames = [bytes([i + 1]) * s for i, s in enumerate(sizes)]
    cluster = media.element(media.CLUSTER, media.uint(media.CLUSTER_TIME, 1000) + media.element(media.BLOCK_GROUP, media.element(media.BLOCK, _block(lacing, frames))))
    data = media.element(media.EBML, b"") + media.element(media.SEGMENT, cluster)
    p = media.packets(data)
    assert [data[o : o + s] for o, s in zip(p["offset"], p["size"], strict=True)] == frames
    assert p["timestamp"] == [1005] * len(sizes) and p["track"] == [2] * len(sizes)


def test_unknown_sizes():
    inner = media.uint(media.CLUSTER_TIME, 7) + media.element(media.SIMPLE_BLOCK, _block(2, [b"ab", b"cd"]))
    cluster = media.CLUSTER.to_bytes(4, "big") + b"\x01" + b"\xff" * 7 + inner
    data = media.element(media.EBML, b"") + media.SEGMENT.to_bytes(4, "big") + b"\xff" + cluster + cluster
    assert media.packets(data)["size"] == [2, 2, 2, 2] and len(media.packets(data)["clusters"]) == 2
    with pytest.raises(ValueError):
        media.packets(data[:-1])


def test_media_tables(spark, odd_docs):
    files = materialise(media.store(odd_docs), "media")
    n = media.packet_table(files).groupBy("doc_id").sum("byte_size").collect()
    want = {r.doc_id: r for r in media.digests(odd_docs.where("doc_id not in (3)")).collect()}
    for r in n:
        if r.doc_id in want and r.doc_id is not None:
            assert r["sum(byte_size)"] == want[r.doc_id].payload_bytes


def test_digests_against_plain_values(spark, odd_docs):
    """Every contract column, from the texts alone; equal texts have equal values."""
    got = media.digests(odd_docs).collect()
    texts = odd_docs.select("doc_id", "text").collect()
    want = []
    for r in texts:
        raw = (r.text or "").encode()
        payload = raw + bytes(-len(raw) % 64 if raw else 64)
        want.append((r.doc_id, len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:])))
    key = lambda x: tuple(map(str, x))
    assert sorted((tuple(r)[:5] for r in got), key=key) == sorted(want, key=key)
    assert len({tuple(r)[1:] for r in got}) == len({r.text or "" for r in texts})
    files = {r.doc_id: r.media for r in media.store(odd_docs).collect()}
    assert all(r.media_bytes == len(files[r.doc_id]) and r.media_sha256 == hashlib.sha256(files[r.doc_id]).hexdigest() for r in got if r.doc_id not in (3, None))


def test_stages_on_odd_tables(spark, odd_docs, clashing, empty_docs, tmp_path):
    """Each stage by itself on null, empty, long and repeated rows, clashing columns and an empty table, and the whole run on them."""
    where = str(tmp_path)
    spark.createDataFrame([(1, 1, 1), (3, 1, 0), (None, 1, 1), (99, 1, None)], "doc_id long, quality int, toxic int").write.parquet(f"{where}/labels.parquet")
    spark.createDataFrame([(1, "word word word word word word"), (2, None), (3, "same text twice")], "item_id long, text string").write.parquet(f"{where}/benchmark.parquet")
    rows = odd_docs.count()
    kept = {"near_copies": rows - 4, "decontamination": rows - 1, "personal_data": rows, "token_ids": rows}  # two blank texts and two copies go
    for name, stage in corpus_pipeline.STAGES:
        a, b = stage(spark, odd_docs, where), stage(spark, clashing, where)
        if name != "token_ids":
            assert a.columns == odd_docs.columns and b.columns == clashing.columns
        assert a.count() == b.count() == kept.get(name, b.count()), name
        assert stage(spark, empty_docs, where).count() == 0
    odd_docs.write.parquet(f"{where}/documents.parquet")
    assert {r.doc_id for r in corpus_pipeline.run(spark, where).collect()} >= {5, 6, 8, None}


def test_pipeline_stages(spark, small):
    docs = table(spark, small, "documents")
    columns, n = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = materialise(stage(spark, docs, small), name)
        assert out.columns == columns and 0 < out.count() <= docs.count()
        if name == "near_copies":
            assert out.count() == near_copies.near_duplicates(docs).select("root").distinct().count()
        docs = out
    last = corpus_pipeline.run(spark, small)
    assert last.count() == docs.count() < n and last.columns == ["doc_id", "n_tokens", "ids"]
