import numpy as np
from divknn.llm import licenses
from divknn.llm.common import table

from .helpers import AWKWARD, docs

FOLDED = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


def brute(rows):
    """(document, licence) pairs with a window that contains enough shingles."""
    found = set()
    for k, t in rows:
        w = (t or "").encode().translate(FOLDED).split()
        grams = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        for name, text in licenses.TEMPLATES.items():
            own = text.encode().translate(FOLDED).split()
            need, width = {tuple(own[i : i + 5]) for i in range(len(own) - 4)}, len(own) - 4
            if not need & set(grams):
                continue
            if any(len(need & set(grams[i : i + width])) >= 0.8 * len(need) for i in range(len(grams) - width + 1)):
                found.add((k, name))
    return found


def check(df):
    got = licenses.license_matches(df).collect()
    assert {(r["doc_id"], r["license"]) for r in got} == brute([(r[0], r[1]) for r in df.select("doc_id", "text").collect()])
    return got


def test_given_documents(spark):
    assert check(table(spark, "/root/testdata/sf0.01", "documents"))


def test_variants(spark):
    bsd = licenses.TEMPLATES["BSD-notice"]
    changed = bsd.replace("conditions are met", "terms are met").upper()
    rows = [(50, f"x {bsd} y {bsd}"), (51, changed), (52, bsd[: len(bsd) // 2]), (53, "Released### under*** the&&& MIT%%% License."), (54, "under the MIT License")]
    got = check(docs(spark, AWKWARD + rows))
    assert sum(r["doc_id"] == 50 for r in got) == 2 and any(r["doc_id"] == 51 for r in got) and any(r["doc_id"] == 53 for r in got)
    assert check(docs(spark, [])) == []


def test_band_settings():
    j = licenses.CONTAINED / (2 - licenses.CONTAINED)
    assert (1 - j**licenses.ROWS) ** licenses.BANDS < 1e-5
    rng = np.random.default_rng(0)
    grams = rng.integers(0, 1 << 63, (200, 20)).astype(np.uint64)
    other = grams.copy()
    other[:, :4] = rng.integers(0, 1 << 63, (200, 4)).astype(np.uint64)
    hit = np.zeros(200, bool)
    for a, b in zip(licenses.TemplateIndex.keys(grams), licenses.TemplateIndex.keys(other), strict=True):
        hit |= np.array([x == y for x, y in zip(a, b, strict=True)])
    assert hit.all()
