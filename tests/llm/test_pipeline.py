import random

import corpus_pipeline

from blocksketch.llm import packing


def test_run_equals_a_plain_version(spark, tmp_path):
    """rate is 0.5 and the draw hashed, so the plain version takes the mixture's choice from the stage and checks all else by itself."""
    rng = random.Random(1)
    vocab = {lang: ["".join(rng.choice(letters) for _ in range(rng.randint(2, 7))) for _ in range(80)] for lang, letters in (("en", "theran"), ("de", "schugü"))}
    rows = []
    for k in range(40):
        lang = ("en", "de")[k % 2]
        rows.append((k, " ".join(rng.choice(vocab[lang]) for _ in range(60)), lang, f"s{k % 3}", 0))
    rows += [(100 + k, rows[k][1], *rows[k][2:]) for k in range(10)]  # copies
    rows += [(200, "12 34 !!", "en", "s0", 0), (201, None, "en", "s0", 0), (202, rows[0][1].replace(" ", " mail a.b@c.org ", 1), "en", "s1", 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    df.write.parquet(str(tmp_path / "documents.parquet"))
    docs, seen = spark.read.parquet(str(tmp_path / "documents.parquet")), {}
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, str(tmp_path))
        docs.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        seen[name] = docs.collect()
        assert name == "packing" or docs.columns == df.columns
    ids = {name: {r.doc_id for r in got} for name, got in seen.items()}
    every = {r[0] for r in rows}
    assert ids["language_id"] == every - {200, 201}
    assert ids["near_duplicates"] == every - {200, 201, *range(100, 110), 202}
    assert ids["personal_data"] == ids["near_duplicates"] and ids["mixing"] <= ids["personal_data"]
    enc = packing.encoder(packing.VOCABULARY)
    total = {r.doc_id: len(enc.slow.encode(r.text, add_special_tokens=False).ids) + 1 for r in seen["mixing"]}
    got = {}
    for r in seen["packing"]:
        got[r.doc_id] = got.get(r.doc_id, 0) + r.length
    assert got == total
    whole = corpus_pipeline.run(spark, str(tmp_path))
    key = lambda rows: sorted((r.doc_id, r.start, r.length, r.ids_crc32) for r in rows)
    assert key(whole.collect()) == key(seen["packing"])
