import zlib
from array import array
from collections import Counter, defaultdict

from tokenizers import Tokenizer

import corpus_pipeline as p
from tests.llm.test_operators import PLANTED, brute_classes, runs_over
from zspan.llm import linededup

SF = "/root/testdata/sf0.001"


def test_stages(spark, monkeypatch):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    rows = {r["doc_id"]: r for r in docs.collect()}
    assert [len(x) for x in p.STAGES] == [2] * 5

    first = p.language_id(spark, docs, SF)
    assert first.columns == columns and {r["doc_id"] for r in first.collect()} == set(rows)  # no clean document goes

    second = p.line_dedup(spark, docs, SF)
    got = {r["doc_id"]: r for r in second.collect()}
    seen, want = set(), {}
    for i in sorted(rows):
        kept = []
        for c in linededup.chunks(rows[i]["text"]):
            if linededup.counts_as_repeatable(c):
                if c.strip() in seen:
                    continue
                seen.add(c.strip())
            kept.append(c)
        if "".join(kept).strip():
            want[i] = "".join(kept)
    assert second.columns == columns and {i: r["text"] for i, r in got.items()} == want
    assert all(r["n_chars"] == len(r["text"]) for r in got.values())

    third = p.near_duplicates(spark, docs, SF)
    ids = sorted(rows)
    classes = brute_classes([rows[i]["text"] for i in ids])
    assert third.columns == columns and {r["doc_id"] for r in third.collect()} == {ids[c] for c, _, _ in classes.values()}

    fourth = p.secrets(spark, docs, SF)
    plain = {i: PLANTED.sub(lambda m: m.group().replace(m.group(m.lastindex), "[secret]"), r["text"]) for i, r in rows.items()}
    assert fourth.columns == columns and {r["doc_id"]: (r["text"], r["n_chars"]) for r in fourth.collect()} == {i: (t, len(t) if t != rows[i]["text"] else rows[i]["n_chars"]) for i, t in plain.items()}

    kept, write = [], p.written
    monkeypatch.setattr(p, "written", lambda df, name: kept.append(write(df, name)) or kept[-1])
    used, pieces = Counter(), defaultdict(list)
    for r in p.run(spark, SF).collect():
        used[r["sequence_id"]] += r["length"]
        pieces[r["doc_id"]].append(r)
    assert len(kept) == 4 and max(used.values()) <= 2048 and len(used) <= -(-used.total() // 2048) + 1
    tok, texts = Tokenizer.from_file(p.VOCABULARY), {r["doc_id"]: r["text"] for r in kept[-1].collect()}
    assert set(pieces) == set(texts) and len(set(rows) - set(texts)) < len(rows) / 2
    for i, t in texts.items():  # every piece of what the stage before kept holds the library's ids
        ids, at = array("I", [*tok.encode(t, add_special_tokens=False).ids, 0]), 0
        for k, r in enumerate(sorted(pieces[i], key=lambda r: r["piece"])):
            assert (r["piece"], r["start"], r["ids_crc32"]) == (k, at, zlib.crc32(ids[at : at + r["length"]].tobytes()))
            at += r["length"]
        assert at == len(ids)


def test_line_dedup_stage_leaves_no_repeated_passage(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    texts, seen, want = {r["doc_id"]: r["text"] for r in docs.collect()}, set(), {}
    for i in sorted(texts):
        lines = texts[i].split("\n")
        runs = runs_over(lines)
        lost = {k for (a, b), x in runs.items() if x in seen for k in range(a, b)}
        seen |= set(runs.values())
        want[i] = Counter(x for k, x in enumerate(lines) if k not in lost and x.strip())
    got = {r["doc_id"]: Counter(x for x in r["text"].split("\n") if x.strip()) for r in dict(p.STAGES)["line dedup"](spark, docs, SF).collect()}
    assert all(not got.get(i, Counter()) - want[i] for i in texts)
    assert {x.strip() for c in got.values() for x in c} == {x.strip() for t in texts.values() for x in t.split("\n") if x.strip()}  # nothing goes everywhere
