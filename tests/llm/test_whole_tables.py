"""The codec and the stages of the pipeline over whole tables."""

SF = "/root/testdata/sf0.001"


def test_codec_parity_on_every_document(spark):
    from tilesketch.llm import sentencepiece_codec as codec

    texts = [r.text or "" for r in spark.read.parquet(f"{SF}/documents.parquet").select("text").collect()]
    model = codec.model_bytes()
    assert len(texts) >= 200 and codec.parity(model, texts) == []
    out = codec.encoded(spark.read.parquet(f"{SF}/documents.parquet"), model)
    assert out.where("round_trip").count() == len(texts)


def test_pipeline_stages_keep_the_right_rows(spark):
    import corpus_pipeline as pipe
    from tests.llm.test_operators import components, shingles

    white = " \t\n\r\x0b\x0c"
    given = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {r.doc_id: r.text for r in given.collect()}
    seen, lines = set(), {}
    for i in sorted(rows):
        parts = (rows[i] or "").split("\n")
        full = [n for n, x in enumerate(parts) if x.strip(white)]
        gone = set()
        for three in zip(full, full[1:], full[2:]):
            key = tuple(parts[n].strip(white) for n in three)
            if key in seen:
                gone |= set(three)
            seen.add(key)
        rest = "\n".join(x for n, x in enumerate(parts) if n not in gone) if rows[i] is not None else None
        if not gone or rest.strip(white):
            lines[i] = rest
    assert {r.doc_id: r.text for r in pipe.line_stage(spark, given, SF).collect()} == lines

    sets = {i: shingles(t) for i, t in rows.items()}
    linked = [(a, b) for a in sets for b in sets if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])]
    top = components(list(rows.items()), linked)
    assert linked
    assert sorted(r.doc_id for r in pipe.near_duplicate_stage(spark, given, SF).select("doc_id").collect()) == sorted(i for i in rows if top[i] == i)

    bench = [r.text for r in spark.read.parquet(f"{SF}/benchmark.parquet").select("text").collect() if r.text]
    kept = {r.doc_id for r in pipe.decontamination_stage(spark, given, SF).select("doc_id").collect()}
    verbatim = {i for i, t in rows.items() if any(b in (t or "") for b in bench)}
    assert verbatim and not kept & verbatim
