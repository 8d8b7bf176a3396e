"""What was open after round 3 in the training-data operators; each test fails before its change."""

from __future__ import annotations

import random

import pyarrow as pa
import pytest
import public_tokenizers

from comotion.llm import packing, queries, repeats

WORDS = public_tokenizers.path("word_bpe_49k.json")


@pytest.mark.parametrize("most", [1_000_000, 3])
def test_plain_words_are_encoded_once_and_held_in_arrays(monkeypatch, most):
    """Words of letters are encoded once whatever marks follow them, and none of them is looked up as a Python string."""
    from tokenizers import Tokenizer

    monkeypatch.setattr(packing, "PLAIN", most, raising=False)
    plain = Tokenizer.from_file(WORDS)
    plain.encode_special_tokens = True
    rng, t = random.Random(8), packing.Tokens(WORDS)
    alphabet = ["a", "b", "S", "é", "É", "ß", "×", "ÿ", ".", ",", "<", "|", "'", "'s", '"', "  ", " ", "\n", "3", "日", "İ", "̇", "̸", "Ω", "<|endoftext|>", "_", "\x00", "\x85"]
    for _ in range(6):
        texts = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 12))) for _ in range(200)] + [None, "", " ", "Ja! " * 9 + "." * 20 + "x" + "." * 20]
        column = pa.array(texts).slice(rng.randint(0, 3))
        ids, offsets = t.packed(column)
        for k, text in enumerate(column.to_pylist()):
            assert ids[offsets[k] : offsets[k + 1]].tolist() == plain.encode(text or "", add_special_tokens=False).ids, text
    t = packing.Tokens(WORDS)
    t.packed(pa.array(["One two, two. two!? (one) Über, été;", "two; TWO one..."]))
    assert not {"one", "two", "two,", "two."} & set(t.memo)
    assert sorted(t.plain[0].to_pylist()) == (["one", "two", "Über", "été"] if most > 3 else [])


def passage_bytes(rows, least):
    """(bytes, runs) that strings of ``least`` bytes cover which occur again, by brute force."""
    raw = [(t or "").encode() for _, t in rows]
    seen, out = {}, []
    for b in raw:
        for i in range(len(b) - least + 1):
            seen[b[i : i + least]] = seen.get(b[i : i + least], 0) + 1
    for (d, _), b in zip(rows, raw):
        runs = []
        for i in range(len(b) - least + 1):
            if seen[b[i : i + least]] > 1:
                if runs and i <= runs[-1][1]:
                    runs[-1][1] = i + least
                else:
                    runs.append([i, i + least])
        out.append((d, len(b), sum(z - a for a, z in runs), len(runs)))
    return sorted(out)


@pytest.mark.parametrize("large", [repeats.LARGE, 3])
def test_two_lengths_in_one_run(spark, small, monkeypatch, large):
    """Repeats of 400 and of 250 bytes, both as by brute force, from one run."""
    monkeypatch.setattr(repeats, "LARGE", large)
    rng = random.Random(4)
    junk = lambda n: "".join(rng.choice("xyzw ") for _ in range(n))
    long, middle, near = junk(700), junk(300), junk(520)
    rows = [(k, junk(rng.randint(0, 300)) + long[rng.randint(0, 300) : rng.randint(500, 700)] + junk(rng.randint(0, 90))) for k in range(9)]
    rows += [(20 + k, junk(rng.randint(0, 200)) + middle[rng.randint(0, 70) :] + junk(rng.randint(0, 200))) for k in range(9)]
    rows += [(40 + k, near[:260] + "é" * (k % 3) + near[260:]) for k in range(5)]
    rows += [(60, "ab" * 700), (61, middle[:249]), (62, middle[:250]), (63, None), (63, None), (64, ""), (65, middle), (65, middle)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").unionByName(spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text").limit(40))
    every = [(r.doc_id, r.text) for r in docs.collect()]
    got = repeats.strip(docs, short=250).collect()
    assert sorted((r.doc_id, r.n_bytes, r.n_removed, r.n_spans) for r in got) == passage_bytes(every, 400)
    assert sorted((r.doc_id, r.n_bytes, r.n_passage_bytes, r.n_passages) for r in got) == passage_bytes(every, 250)


def test_short_passages_show_in_the_query(spark, tmp_path):
    """Passages of over fifty words and under 400 bytes don't go from the text, but the row counts them."""
    rng = random.Random(2)
    words = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randint(4, 6))) for _ in range(n))
    passage = words(55)
    spark.createDataFrame([(1, f"{words(40)} 1 {passage} 1 {words(30)}"), (2, f"{words(9)} 2 {passage} 2"), (3, words(90))], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    got = {r.doc_id: r for r in queries.op2_repeated_passages(spark, str(tmp_path)).collect()}
    assert [got[k].n_removed for k in (1, 2, 3)] == [0, 0, 0]
    assert [got[k].n_passage_bytes for k in (1, 2, 3)] == [len(passage) + 2, len(passage) + 2, 0] and got[1].n_passages == 1
