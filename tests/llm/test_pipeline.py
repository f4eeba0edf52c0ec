import corpus_pipeline
import numpy as np
from divknn.llm import decontaminate, quality
from divknn.llm.common import FOLD, table, word_hashes

from .test_jaccard_join import brute as brute_groups
from .test_quality import brute as brute_stats
from .test_secrets import brute as brute_spans
from .test_tokens import check_packing, crc, ids_of


def test_against_brute_force(spark):
    d = "/root/testdata/sf0.001"
    rows = [(r[0], r[1], r[2]) for r in table(spark, d, "documents").select("doc_id", "text", "lang").collect()]
    cutoffs = quality.certified_cutoffs(quality.scored(table(spark, d, "documents")), table(spark, d, "labels"))

    def good(text, lang):
        n, chars, symbols, dup, repeats, failed = brute_stats(text)
        lines = sum(bool(x.strip(" \t\n\r\x0b\x0c")) for x in text.split("\n"))
        upper = sum("A" <= c <= "Z" for c in text)
        score = {"symbols": min(400, 400 * symbols // max(1, chars)), "repeats": min(400, 400 * repeats // max(1, n)), "dup_lines": min(400, 400 * dup // max(1, lines)), "upper": min(400, 400 * upper // max(1, chars)), "short": max(0, 400 - n)}
        return not failed and all(score[r] < t for r, t in cutoffs.get(lang, {}).items())

    rows = [(k, t) for k, t, lang in rows if good(t, lang)]
    first = {int(k) for k, _, c in brute_groups(rows) if k == c}
    rows = [(k, t) for k, t in rows if k in first]
    items = [word_hashes([r["text"].encode().translate(FOLD)])[0] for r in table(spark, d, "benchmark").collect()]

    def leaks(text):
        h = word_hashes([text.encode().translate(FOLD)])[0]
        return any(len(np.intersect1d(i, h)) >= len(np.unique(i)) - len(i) // 5 and decontaminate.edit_place(i, h)[0] <= len(i) // 5 for i in items)

    rows = [(k, t) for k, t in rows if not leaks(t)]

    def hidden(text):
        out, at = "", 0
        for s, _, e, _ in sorted(brute_spans(text)[0]):
            if s >= at:
                out += text[at:s] + "[SECRET]"
            at = max(at, e)
        return out + text[at:]

    want = []
    for k, ids in ids_of([(k, hidden(t)) for k, t in rows], 1):
        want += [(k, i, s, len(ids[s : s + 4096]), crc(ids[s : s + 4096])) for i, s in enumerate(range(0, len(ids), 4096))]
    check_packing(corpus_pipeline.run(spark, d).collect(), want, 4096)


def test_stages_keep_the_columns(spark):
    d = "/root/testdata/sf0.001"
    docs = table(spark, d, "documents")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, d).schema.simpleString() == docs.schema.simpleString(), name
        assert stage(spark, docs.limit(0), d).count() == 0
