import hashlib
import itertools
import random
import zlib

import pytest
import xxhash
from pyspark.sql import functions as F

from stationlink.llm import chat, fingerprint, html_extract, mixing, sharding
from stationlink.llm.queries import QUERIES

SMALL = "/root/testdata/sf0.001"


def test_shards_equal_a_global_sort(spark):
    r = random.Random(1)
    rows = [(k, r.choice(["same text"] * 3 + [None, "", "ü" * r.randint(1, 50), "x" * r.randint(1, 900)])) for k in range(700)] + [(None, "no id"), (3, "again"), (3, "again")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("shard", F.lit("clash"))
    got = sharding.shard_by_bytes(df, 16, sample=300).collect()
    signed = lambda x: x - (1 << 64) if x >= 1 << 63 else x
    key = [(signed(xxhash.xxh64((t or "").encode(), seed=42).intdigest()), -(1 << 63) if k is None else k, len((t or "").encode()) + 1, zlib.crc32((t or "").encode()), k) for k, t in rows]
    total, at, want, number = sum(x[2] for x in key), 0, [], {}
    for h, i, size, crc, k in sorted(key, key=lambda x: x[:4]):
        s = min(15, (2 * at + size) * 16 // (2 * total))
        want.append((k, size, crc, s, number.setdefault(s, 0)))
        number[s] += 1
        at += size
    assert sorted(((x.doc_id, x["size"], x.text_crc32, x.shard, x.slot) for x in got), key=repr) == sorted(want, key=repr)
    assert sharding.shard_by_bytes(df.limit(0), 16).count() == 0


def test_flow_has_the_least_repetition_cost():
    r = random.Random(11)
    for _ in range(60):
        patterns = {p: r.randint(1, 3) for p in r.sample([(0,), (1,), (2,), (0, 1), (1, 2), (0, 1, 2)], r.randint(1, 3))}
        quotas = [r.randint(0, 4) for _ in range(3)]
        got = mixing.flow(patterns, quotas)
        arcs = [(p, s) for p in patterns for s in p]
        best = None
        for amounts in itertools.product(range(5), repeat=len(arcs)):  # every whole flow
            into, out = [0] * 3, dict.fromkeys(patterns, 0)
            for (p, s), n in zip(arcs, amounts):
                into[s] += n
                out[p] += n
            if all(x <= q for x, q in zip(into, quotas)) and all(out[p] <= 3 * n for p, n in patterns.items()):
                cost = sum((k // patterns[p]) ** 2 for p, n in out.items() for k in range(n))
                best = min(best or (0, 1 << 30), (-sum(into), cost))
        assert all(sum(n for (_, t), n in got.items() if t == s) <= quotas[s] for s in range(3))
        used = {p: sum(n for (q, _), n in got.items() if q == p) for p in patterns}
        assert all(used[p] <= 3 * n for p, n in patterns.items())
        assert (-sum(used.values()), sum((k // patterns[p]) ** 2 for p, n in used.items() for k in range(n))) == best
    many = {(k % 3000, 3000 + k): 10 for k in range(6000)} | {(k,): 5 for k in range(20_000, 60_000)}
    assert sum(mixing.flow({p: n for p, n in many.items() if len(p) == 1}, [5] * 60_000).values()) == 200_000


def test_targets_stop_at_three_times_a_source():
    got = mixing.targets([("a", 10), ("b", 1000), ("c", 1000)], [1, 2, 3])
    assert got[0] == 30 and sum(got) == pytest.approx(2010) and got[2] / got[1] == pytest.approx(1.5)


def test_mix_takes_whole_documents_near_each_quota(spark, monkeypatch):
    rows = [(k, k % 17, ["a"] if k % 3 else ["a", "b"]) for k in range(600)] + [(None, 5, ["b"]), (700, 4, [None]), (701, 9, [])]
    df = spark.createDataFrame(rows, "key long, size long, sources array<string>").withColumn("copies_of", F.lit(1))
    got = mixing.mix(df, [("a", 5000.0), ("b", 1500.0), (None, 8.0)]).collect()
    assert len(got) == len(rows) and all(0 <= r.copies <= 3 for r in got)
    assert abs(sum(r.copies * r["size"] for r in got) - 6508) < 60
    assert {r.key: r.copies for r in got}[701] == 0 and {r.key: r.copies for r in got}[700] == 2
    quotas = [("a", 5000.0), ("b", 1500.0), (None, 8.0)]
    want = sorted((str(r.key), r.copies) for r in got)
    assert sorted((str(r.key), r.copies) for r in mixing.mix(df.repartition(7), quotas).collect()) == want
    clash = df.withColumns({c: F.lit(9) for c in ("p", "u", "lo", "last", "row", "some", "whole", "copies", "__p")})
    found = mixing.mix(clash, quotas)
    assert found.columns == [c for c in clash.columns if c != "copies"] + ["copies"] and sorted((str(r.key), r.copies) for r in found.collect()) == want
    assert mixing.mix(df.limit(0), quotas).count() == 0
    monkeypatch.setattr(mixing.Mix, "FEW", 0)  # parts are cut again until they can't be
    monkeypatch.setattr(mixing, "BINS", 16)
    assert sorted((str(r.key), r.copies) for r in mixing.mix(df, quotas).collect()) == want


def test_chat_round_trip(spark):
    r = random.Random(2)
    parts = ["<", "|", "<|im_end|>", "<|im_start|>", "assistant", "\n", "ok", "%0A", "%", "\\", "$1", "é"]
    make = lambda: "".join(r.choice(parts) for _ in range(r.randint(0, 8)))
    rows = [(c, t, r.choice(["user", "assistant", "system", make()]), r.choice([None, make(), make()])) for c in range(40) for t in range(r.randint(1, 6))] + [(None, 0, None, None), (77, None, "assistant", "x"), (77, None, "assistant", "x")]
    df = spark.createDataFrame(rows, "conv_id long, turn int, role string, text string").withColumn("turns", F.lit(0))
    got = {x.conv_id: x for x in chat.read_back(chat.expand(df)).collect()}
    for c in {x[0] for x in rows}:
        own = sorted([((t is not None, t or 0), a or "", b or "") for k, t, a, b in rows if k == c])
        assert got[c].n_turns == len(own) and got[c].turns_text == "".join(f"{a}\n{b}\n" for _, a, b in own)
        assert got[c].loss_text == "".join(b for _, a, b in own if a == "assistant")
    assert chat.read_back(chat.expand(df.limit(0))).count() == 0


def _hash(x, seed=42):
    return xxhash.xxh64(x, seed=seed).intdigest()


def _packed(hashes, lanes):
    """Lanes of 16 bits as longs of four: a byte's bit j of 64 goes to lane (2 j + byte % 2) * 4 + byte // 2."""
    out = [0] * lanes
    for h in hashes:
        for k in range(lanes // 64):
            own = h if k == 0 else _hash(k.to_bytes(4, "little"), _hash(h.to_bytes(8, "little")))
            for bit in range(64):
                byte, j = divmod(bit, 8)
                at = 64 * k + (2 * j + byte % 2) * 4 + byte // 2
                out[at] = (out[at] + (own >> bit & 1)) % (1 << 16)
    return [sum(x << 16 * i for i, x in enumerate(out[k : k + 4])) for k in range(0, lanes, 4)]


def _lanes(text):
    text = text or ""
    wide = [0] * fingerprint.WIDE
    for p in text.split("\n"):
        if p.strip(" "):
            digest = hashlib.sha256(p.encode()).hexdigest().encode()
            wide = [(w + (_hash(digest, _hash(k.to_bytes(4, "little"))) & 0xFFFFFFFF)) % (1 << 32) for k, w in enumerate(wide)]
    pieces = text
    for m in fingerprint.MARKS:
        pieces = pieces.replace(m, m + "\n")
    pieces = [q for p in pieces.split("\n") for q in ([p] if len(p) <= fingerprint.LONG else [p[i : i + fingerprint.PART] for i in range(0, len(p), fingerprint.PART)]) if q]
    lines = (" " + text.replace("\n", " \n ") + " ").split("\n")
    runs = [p[i : i + 3] for p in lines for i in range(len(p) - 2)] if len(text) <= fingerprint.SHORT else None
    out = "".join(f"{x:08x}" for x in wide)
    for found, lanes in ((pieces, fingerprint.LANES), (runs, fingerprint.SHORT_LANES)):
        out += f"{len(found or []):08x}" + ("" if found is None else "".join(f"{x:016x}" for x in _packed([_hash(p.encode()) for p in found], lanes)))
    return out


def test_fingerprints_equal_brute_force_and_next_rows(spark):
    r = random.Random(7)
    line = lambda: " ".join(r.choice(["ab.", "cd", "é!", "x|", "y"]) for _ in range(r.randint(0, 9)))
    rows = [(k * 3 % 997, "\n".join(line() for _ in range(r.randint(0, 6)))) for k in range(120)] + [(2000, None), (2001, ""), (5000, "twin"), (5000, "twin b"), (None, "z")]
    rows += [(6000, "ab. " * 700), (6001, "".join(f"w{k} " for k in range(900)))]  # more pieces than are summed at once; one long line
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("range", F.lit("clash")).withColumn("fp", F.lit(1))
    old, fingerprint.ROWS_PER_RANGE = fingerprint.ROWS_PER_RANGE, 5
    try:
        got = fingerprint.with_next(df).select("doc_id", "text", fingerprint.written(F.col("fp")).alias("fp"), "next_text", fingerprint.written(F.col("next_fp")).alias("next_fp")).collect()
    finally:
        fingerprint.ROWS_PER_RANGE = old
    order = sorted(((-(1 << 63) if k is None else k, t or "") for k, t in rows), reverse=True)
    want = sorted((k, t, _lanes(t), order[(i + 1) % len(order)][1], _lanes(order[(i + 1) % len(order)][1])) for i, (k, t) in enumerate(order))
    assert sorted((-(1 << 63) if x.doc_id is None else x.doc_id, x.text, x.fp, x.next_text, x.next_fp) for x in got) == want


def test_fingerprint_query_equals_its_definition(spark):
    docs = {r.doc_id: r.text or "" for r in spark.read.parquet(f"{SMALL}/documents.parquet").collect()}
    ids = sorted(docs, reverse=True)
    following = {k: docs[ids[(i + 1) % len(ids)]] for i, k in enumerate(ids)}
    got = QUERIES["op8_multiset_fingerprint"](spark, SMALL).collect()
    assert sorted(r.doc_id for r in got) == sorted(ids)
    better = 0
    for r in got:
        text = docs[r.doc_id]
        third = len(text) // 3
        edited = text[: len(text) - third] + following[r.doc_id][:third]
        assert r.n_chars == len(text) and r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert r.fingerprint == _lanes(text) and r.edited_fingerprint == _lanes(edited)
        better += r.near_edited > r.near_next
    assert better / len(got) >= 0.99


def test_fingerprint_query_on_an_empty_table(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert fingerprint.with_next(none).count() == 0


def test_fingerprints_add_remove_and_ignore_order(spark):
    texts = {"a": "one\ntwo", "b": "three", "ab": "three\n\none\ntwo", "p": "p.\nq", "q": "q\np.", "e": "", "n": None}
    r = random.Random(5)
    sentence = lambda: " ".join("".join(r.choice("abcdefghij") for _ in range(5)) for _ in range(6)) + ". "
    long = [sentence() for _ in range(600)]
    texts |= {"l": "".join(long), "half": "".join(long[:300]) + "".join(sentence() for _ in range(300)), "other": "".join(sentence() for _ in range(600)), "x12": "".join(sentence() for _ in range(12)), "y12": "".join(sentence() for _ in range(12))}
    row = spark.createDataFrame([tuple(texts.values())], ", ".join(f"{k} string" for k in texts)).select(*[fingerprint.lanes(f"`{k}`").alias(k) for k in texts])
    like = lambda a, b: fingerprint.likeness(a, b).alias(f"{a}_{b}")
    same = lambda a, b: (F.col(a) == F.col(b)).alias(f"{a}_{b}_same")
    got = row.select(
        (fingerprint.added("a.wide", "b.wide") == F.col("ab.wide")).alias("sum"), (fingerprint.removed("ab.wide", "b.wide") == F.col("a.wide")).alias("less"), same("p", "q"),
        like("ab", "ab"), like("a", "b"), like("e", "n"), like("e", "a"), like("l", "half"), like("l", "other"), like("x12", "y12"), like("l", "l"),
        (fingerprint.read(fingerprint.written(F.col("l"))) == F.col("l")).alias("read_long"), (fingerprint.read(fingerprint.written(F.col("a"))) == F.col("a")).alias("read_short"),
    ).first()
    assert got.sum and got.less and got.p_q_same and got.read_long and got.read_short
    assert got.ab_ab == got.e_n == got.l_l == 1 and got.e_a == 0 and got.a_b < 0.4
    assert abs(got.l_half - 0.5) < 0.2 and got.l_other < 0.3 and got.x12_y12 < 0.4  # whatever the number of pieces


def test_main_text_of_unseen_layouts():
    model, right, total = html_extract.trained(), 0, 0
    for page in html_extract.labelled_pages(60, 4242):
        blocks = html_extract.leaf_blocks(page)
        for b, main in zip(blocks, model.decode(blocks)):
            total, right = total + 1, right + (main == bool(b.label))
    assert right / total > 0.98


def test_extraction_of_edge_cases(spark):
    rows = [(1, "u", None), (2, None, ""), (3, "u", "<p"), (4, "u", "<article><h1>A &amp; B</h1><p>x\n  y<br>z</p><script>no</script><!-- no --><p>&#233;t&eacute;</article>"), (4, "u", "<body><nav><a href=x>menu</a></nav>")]
    got = sorted(html_extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", F.lit(1))).collect(), key=lambda r: (r.page_id, r.text))
    texts = {(r.page_id, r.text) for r in got}
    assert texts - {(3, "p"), (3, "<p")} == {(1, ""), (2, ""), (4, "A & B x y z été"), (4, ""), *[t for t in texts if t[0] == 3 and t[1] == ""]}
    more = [(5, "u", "<article><h1>Title here</h1><p>The area <math><mi>x</mi></math> of it <svg><text>is drawn</text></svg> and so on.</p></article>"), (6, "u", "<article><p>Before it.<script>a</p><p>After the open script there is text.</p></article>"), (7, "u", "<article><p>" + "A long text of one page. " * 40_000 + "</p></article>")]
    read = {r.page_id: r.text for r in html_extract.extract(spark.createDataFrame(more, "page_id long, url string, html string")).collect()}
    assert "area x of it is drawn and so on." in read[5] and "After the open script there is text." in read[6] and len(read[7]) == 40_000 * 25 - 1
    assert html_extract.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0
