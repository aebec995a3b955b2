from curvetide.llm import mixing as M


def expected_targets(sizes):
    order = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    w = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    total, out, free = 1.5 * sum(sizes.values()), {}, set(order)
    while free:
        rest, weight = total - sum(out.values()), sum(w[s] for s in free)
        over = [s for s in free if rest * w[s] / weight > 2 * sizes[s] + 1e-9]
        if not over:
            return out | {s: rest * w[s] / weight for s in free}
        for s in over:
            out[s] = 2.0 * sizes[s]
            free.discard(s)
    return out


def corpus(spark):
    rows, i = [], 0
    for source, n, size in (("b", 40, 30), ("a", 7, 3), ("é", 1, 900), (None, 20, 25), ("Z", 3, 0), ("c", 1, 20000)):
        for k in range(n):
            rows.append((i, " \n".join(f"{source}{i}_{j}" for j in range(size + k % 3 if size else 0)) or (None if k else ""), source, 1))
            i += 1
    return spark.createDataFrame(rows, "doc_id long, text string, source string, target long")


def test_targets_and_taken(spark):
    df = corpus(spark)
    rows = M.mix(df, block=16).collect()
    sizes = {}
    for r in rows:
        sizes[r["source"]] = sizes.get(r["source"], 0) + r["size"]
    want = expected_targets(sizes)
    for s in sizes:
        mine = [r for r in rows if r["source"] == s]
        assert all(abs(r["target"] - want[s]) < 1e-6 and r["source_size"] == sizes[s] for r in mine)
        assert abs(sum(r["taken"] for r in mine) - want[s]) <= 0.5
    for r in rows:
        assert r["taken"] <= 2 * r["size"] and r["taken"] == sum(p["hi"] - p["lo"] for p in r["pieces"])
        words = [(p["epoch"], k) for p in r["pieces"] for k in range(p["lo"], p["hi"])]
        assert len(words) == len(set(words))
    key = lambda r: (r["doc_id"], r["taken"], str(r["pieces"]))
    assert sorted(map(key, rows)) == sorted(map(key, M.mix(df.repartition(7), block=16).collect()))


def test_texts(spark):
    df = corpus(spark)
    taken = {r["doc_id"]: r["taken"] for r in M.mix(df, block=16).collect()}
    out = M.mixed_texts(df, block=16)
    assert out.columns == df.columns
    n = {}
    full = {r["doc_id"]: (r["text"] or "").split() for r in df.collect()}
    for r in out.collect():
        words = r["text"].split()
        assert set(words) <= set(full[r["doc_id"]])
        n[r["doc_id"]] = n.get(r["doc_id"], 0) + len(words)
    assert n == {k: v for k, v in taken.items() if v}


def test_edges(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, source string")
    assert M.mix(empty).count() == 0
    none = spark.createDataFrame([(1, None, None), (2, "", "a")], "doc_id long, text string, source string")
    assert [(r["size"], r["taken"], r["target"]) for r in M.mix(none).collect()] == [(0, 0, 0.0)] * 2
    twice = spark.createDataFrame([(1, "a b c", "s"), (1, "a b c", "s"), (None, "d", "s")], "doc_id long, text string, source string")
    rows = M.mix(twice).collect()
    assert len(rows) == 3 and sum(r["taken"] for r in rows) == 11 and all(r["taken"] <= 2 * r["size"] for r in rows)


def test_shards_draw_multinomial_counts(spark):
    sizes = {"va": 60_000, "vb": 25_000, "vc": 15_050, "n": 40}
    plan = spark.createDataFrame([(t, k % 2, n, int(1.5 * n)) for k, (t, n) in enumerate(sizes.items())], "tag string, part int, source_size long, want long")
    rows = M.slots(plan, 100, 25, 1).collect()
    assert sorted((r["shard"], r["slot"]) for r in rows) == [(g // 25, g % 25) for g in range(len(rows))]  # all shards are full
    for tag, n in sizes.items():
        mine = [r for r in rows if r["tag"] == tag]
        assert sum(r["words"] for r in mine) == int(1.5 * n) and len({(r["epoch"], r["block"]) for r in mine}) == len(mine)
        assert {r["block"] for r in mine if r["epoch"] == 0} == set(range(-(-n // 100)))
    counts = [sum(1 for r in rows if r["shard"] == k and r["tag"] == "va") for k in range(len(rows) // 25)]
    mean, share = sum(counts) / len(counts), 0.6
    spread = sum((c - mean) ** 2 for c in counts) / len(counts)
    assert abs(mean - 25 * share) < 1 and 0.5 < spread / (25 * share * (1 - share)) < 1.6  # as binomial counts
    assert rows and sorted(map(tuple, rows)) == sorted(map(tuple, M.slots(plan, 100, 25, 1).collect()))


def test_keyed_permutation(spark):
    from pyspark.sql import functions as F

    for n in (1, 2, 3, 5, 64, 65, 1000):
        x = spark.range(n).select(F.col("id"), M.permuted(F.col("id"), F.lit(n).cast("long"), F.lit(7)).alias("a"), M.permuted(F.col("id"), F.lit(n).cast("long"), F.lit(8)).alias("b"))
        rows = x.orderBy("id").collect()
        assert sorted(r["a"] for r in rows) == list(range(n)) == sorted(r["b"] for r in rows)
        if n > 60:
            assert [r["a"] for r in rows] != [r["b"] for r in rows]
            steps = {(q["a"] - p["a"]) % n for p, q in zip(rows, rows[1:])}
            assert len(steps) > n // 4  # not a line


def test_many_sources(spark):
    rows = [(i, "w " * (1 + i % 40), f"host{i % 700}") for i in range(2000)]
    out = M.mix(spark.createDataFrame(rows, "doc_id long, text string, source string"), block=8).collect()
    sizes = {}
    for r in out:
        sizes[r["source"]] = sizes.get(r["source"], 0) + r["size"]
    want = expected_targets(sizes)
    taken = dict.fromkeys(sizes, 0)
    for r in out:
        taken[r["source"]] += r["taken"]
        assert abs(r["target"] - want[r["source"]]) < 1e-6 and r["taken"] <= 2 * r["size"]
    assert all(abs(taken[s] - want[s]) <= 0.5 for s in sizes)


def test_words_by_brute_force(spark):
    """Slots to words: each document's pieces from the slots' blocks over the stream."""
    df = corpus(spark)
    block, rows = 16, M.mix(df, block=16).collect()
    for source in {r["source"] for r in rows}:
        mine = [r for r in rows if r["source"] == source and r["size"]]
        if not mine:
            continue
        # passes of a source take each word once: rebuild the words of a pass from its pieces
        for epoch in {p["epoch"] for r in mine for p in r["pieces"]}:
            words = {(p["shard"], p["slot"]): 0 for r in mine for p in r["pieces"] if p["epoch"] == epoch}
            for r in mine:
                for p in r["pieces"]:
                    if p["epoch"] == epoch:
                        words[p["shard"], p["slot"]] += p["hi"] - p["lo"]
            full = mine[0]["source_size"]
            want = min(full, round(mine[0]["target"]) - epoch * full)
            assert sum(words.values()) == want and max(words.values()) <= block
            assert sum(1 for n in words.values() if n < block) <= 2  # the short block and the last slot
