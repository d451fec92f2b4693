"""The pipeline held against brute force, stage by stage, on a small table."""

import re
import zlib

import numpy as np

import corpus_pipeline
from dyntri.llm import quality, storage

from .test_operators import WORD, brute_components, brute_quality, low

SF = "/root/testdata/sf0.001"


def brute_kept(rows):
    """Ids that the quality rules keep."""
    seen = {}
    for i, t, s in rows:
        n, chars, symbols, dups, _, failed = brute_quality(t)
        lines = len([x for x in t.split("\n") if WORD.search(x)])
        severity = max(symbols / max(n, 1) / 0.2, dups / max(lines, 1) / 0.5, len(re.findall("[A-Z]", t)) / max(len(t), 1) / 0.4, chars / max(n, 1) / 15)
        seen[i] = (s, failed, severity)
    hosts = {}
    for s, failed, severity in seen.values():
        n, bad = hosts.get(s, (0, 0))
        hosts[s] = (n + 1, bad + (failed or severity > 1))
    total, m = sum(n for n, _ in hosts.values()), sum(b for _, b in hosts.values()) / sum(n for n, _ in hosts.values())
    v = sum(n * (b / n - m) ** 2 for n, b in hosts.values()) / total - m * (1 - m) * (len(hosts) - 1) / total
    k = max(1, min(10000, m * (1 - m) / v - 1)) if v > 0 else 10000
    allowed = {s: max(0.75, min(2.0, 1 - 0.25 * ((b + m * k) / (n + k) - m) / np.sqrt(m * (1 - m) / (k + 1)))) for s, (n, b) in hosts.items()}
    return {i for i, (s, failed, severity) in seen.items() if not failed and severity <= allowed[s]}


def test_stages(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality_rules", "ngram_jaccard", "benchmark_decontamination", "source_mixing", "token_output"]
    out, d = {}, docs
    for name, stage in corpus_pipeline.STAGES:
        d = storage.saved(stage(spark, d, SF), name)
        out[name] = d
        if name != "token_output":
            assert d.columns == docs.columns
    ids = {n: sorted(r.doc_id for r in out[n].select("doc_id").collect()) for n in names}
    rows = [(r.doc_id, r.text, r.source) for r in docs.collect()]
    text = {i: t for i, t, _ in rows}
    kept = brute_kept(rows)
    assert set(ids["quality_rules"]) == kept
    groups = brute_components([(i, text[i]) for i in sorted(kept)], 5, 80)
    assert ids["ngram_jaccard"] == sorted(i for i, _, c in groups if i == c)
    split = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+").findall
    windows = set()
    for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect():
        w = split(low(r.text))
        n = min(10, len(w))
        windows |= {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if n else set()
    sizes = {len(w) for w in windows}
    hit = {i for i in ids["ngram_jaccard"] for n in sizes if any(tuple(w[k : k + n]) in windows for w in [split(low(text[i]))] for k in range(len(w) - n + 1))}
    assert ids["benchmark_decontamination"] == sorted(set(ids["ngram_jaccard"]) - hit)
    mixed = ids["source_mixing"]
    assert set(mixed) <= set(ids["benchmark_decontamination"]) and max(mixed.count(i) for i in set(mixed)) <= 2
    words = sum(len(WORD.findall(text[i])) for i in ids["benchmark_decontamination"])
    assert abs(sum(len(WORD.findall(text[i])) for i in mixed) / (1.5 * words) - 1) < 0.1
    tok, start = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")), 0
    for r, i in zip(out["token_output"].orderBy("start").collect(), mixed, strict=True):
        got = np.array(tok.encode(text[i], add_special_tokens=False).ids + [2], np.uint32)
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (i, start, len(got), zlib.crc32(got.tobytes()))
        start += len(got)
