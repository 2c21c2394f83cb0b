"""Characters around passages that the pipeline removes."""


def test_only_cut_characters_go(spark):
    import corpus_pipeline as cp

    passage = "".join(chr(0x4E00 + i) for i in range(60))
    # The last byte of the character before the passage and the first two of the one after it are equal in both texts.
    rows = [(1, "\u4dc1" + passage + "\u5001 end"), (2, "x\ufffdy \u4e01" + passage + "\u5002 \ufffd tail"), (3, "clean \ufffd text"), (4, "plain")]
    docs = spark.createDataFrame([(d, t, "en", "s", len(t)) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    got = {r.doc_id: r.text for r in cp.repeated_substrings(spark, docs, "").collect()}
    assert got == {1: rows[0][1], 2: "x\ufffdy  \ufffd tail", 3: rows[2][1], 4: "plain"}
