from carrierpath.llm import toxicity


def test_model_keeps_all_entries(spark, monkeypatch):
    monkeypatch.setattr(toxicity, "MODEL_TOKENS", 1, raising=False)
    spread = lambda i, stem, k: " ".join(f"{stem}{chr(97 + (i + j) % 8)}" for j in range(k))
    rows = [(i, f"{spread(i, 'vilest', 5)} {spread(i, 'nastys', 5)} here and there" if i % 3 == 0 else f"calm words {spread(i, 'benign', 3)} vilestok vilestum nastysok nastysum here and there") for i in range(600)]
    rows = [(i, t + " " + "".join(chr(110 + int(c)) for c in str(i))) for i, t in rows]  # copies count once
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    model = toxicity.fit(docs, spark.createDataFrame([(i, int(i % 3 == 0)) for i, _ in rows], "doc_id long, toxic int"))
    assert {f"{s}{chr(97 + j)}" for s in ("vilest", "nastys") for j in range(8)} <= set(model.entry)
    beginnings = {w: any(e in model.entry for e in toxicity.entries(w)[1:]) for w in ("vilestok", "vilestum", "nastysok", "nastysum")}
    assert model.spared == {w for w, found in beginnings.items() if found}
