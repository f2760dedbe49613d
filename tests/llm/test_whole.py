"""Cases in which an operator once did less than its whole job."""

import random
import textwrap

from pyspark.sql import functions as F

import corpus_pipeline
from rankflow.llm import licences, neardup
from rankflow.operators import measures


def edited_pair(first: int, words: int) -> tuple[str, str]:
    """Two texts of different words of which one in the middle differs."""
    w = [f"w{first + i}" for i in range(words)]
    return " ".join(w), " ".join(w[: words // 2] + [f"x{first}"] + w[words // 2 + 1 :])


def test_stage_drops_copies_of_four_fifths(spark, sf):
    # 49 words: 40 of 50 shingles are shared; 59: 50 of 60; 44: 35 of 45
    rows = []
    for k, words in enumerate([49] * 20 + [55] * 20 + [59] * 20 + [44] * 5):
        a, b = edited_pair(1000 * k, words)
        rows += [(2 * k, a), (2 * k + 1, b)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    left = {r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, sf).collect()}
    assert left == {2 * k for k in range(65)} | {2 * k + 1 for k in range(60, 65)}
    assert neardup.near_components(docs, percent=85).where("kept").count() == len(rows)


def test_ids_with_several_texts_keep_links_and_texts(spark):
    (a, _), (b, b2), (c, c2), (d, d2), (e, _) = (edited_pair(1000 * k, 100) for k in range(5))
    rows = [(3, a), (5, a), (5, b), (7, b2), (9, c), (9, d), (11, c2), (12, d2), (None, a), (13, ""), (13, a), (None, e), (None, e), (14, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = neardup.near_components(docs).collect()
    assert len(got) == len(rows)
    want = {3: 3, 5: 3, 7: 3, 13: 3, 9: 9, 11: 9, 12: 9, 14: 14, None: None}
    assert all((r.component_id, r.kept) == (want[r.doc_id], r.doc_id is None or r.doc_id == want[r.doc_id]) for r in got)
    left = [tuple(r) for r in neardup.one_of_each_group(docs).collect()]
    assert sorted(left, key=str) == sorted([(3, a), (5, b), (9, c), (9, d), (13, ""), (None, e), (14, None)], key=str)
    alone = spark.createDataFrame([(1, c), (1, d), (2, d)], "doc_id long, text string")
    assert {(r.doc_id, r.component_id) for r in neardup.near_components(alone).collect()} == {(1, 1), (2, 1)}


APACHE = """Licensed under the Apache License, Version 2.0 (the "License");
you may not use this file except in compliance with the License.
You may obtain a copy of the License at

    http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law or agreed to in writing, software
distributed under the License is distributed on an "AS IS" BASIS,
WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
See the License for the specific language governing permissions and
limitations under the License."""


def wrapped(text: str, leader: str = "", width: int = 70) -> str:
    return "\n".join(leader + line for line in textwrap.wrap(text, width, break_long_words=False, break_on_hyphens=False))


def test_wrapped_licences_are_found(spark):
    full = {k: s[0].upper() + s[1:] for k, s in licences.SENTENCES.items()}
    mit = [full["m2"] + ":", full["m3"] + "."]
    bsd = ["1. " + full["b1"] + ".", "2. " + full["b2"] + ".", "3. " + full["b3"] + "."]
    gpl = [full["g2"] + ".", full["g3"] + ". If not, see <https://www.gnu.org/licenses/>."]
    blank = full["a5"].replace("permissions and", "permissions and\n\n")
    texts = {
        "apache-2.0 header": [APACHE, " ".join(APACHE.split()), "\n".join("# " + x for x in APACHE.split("\n")), "/*\r\n" + "\r\n".join(" * " + x for x in APACHE.split("\n")) + "\r\n */"],
        "mit text": ["\n\n".join(map(wrapped, mit)), "\n//\n".join(wrapped(x, "// ") for x in mit)],
        "bsd-2-clause text, bsd-3-clause text": ["\n\n".join(map(wrapped, bsd)), "\n".join(wrapped(x, "-- ", 40) for x in bsd)],
        "gpl-3.0 header": ["\n".join(map(wrapped, gpl)), "\n".join(wrapped(x, "dnl ") for x in gpl)],
        "": [APACHE.replace("See the License", "Read the License"), "Said " + full["m1"], "\n".join(["Licensed under the", "", "MIT license."]), blank],
        "mit notice, rights reserved": ["no sign here\nreleased\tunder the\nMIT License\nALL RIGHTS\n# RESERVED"],
    }
    rows = [(i, t, want) for i, (want, t) in enumerate((want, t) for want, several in texts.items() for t in several)]
    got = licences.scan(spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string")).collect()
    assert {r.doc_id: r.licences for r in got} == {i: want for i, _, want in rows}


def test_near_copies_move_no_text(spark):
    """Before, where the ids looked for were too many to broadcast, all texts were dealt by id."""
    rng = random.Random(8)
    texts = [" ".join(f"w{rng.randrange(10**9)}" for _ in range(1500)) for _ in range(240)]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate([*texts, texts[0] + " end"])], "doc_id long, text string").repartition(3).cache()
    docs.count()
    kept = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        last = measures.stage_totals(spark)["last_stage"]
        got = {r.doc_id: r.component_id for r in neardup.near_components(docs).collect()}
        moved = measures.stage_totals(spark, last)["shuffle_bytes"]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", kept)
    assert got == {i: i % 240 for i in range(241)}
    assert moved < sum(map(len, texts)) / 3


def test_ids_that_are_looked_for_are_all_found(spark):
    docs = spark.range(-40_000, 40_000).select(F.col("id").alias("doc_id"), F.lit("x").alias("text"))
    ids = spark.range(-40_000, 40_000, 7).select(F.col("id").alias("doc_id"))
    got = [r.doc_id for r in neardup._perhaps_among(docs, ids).select("doc_id").collect()]
    wanted = set(range(-40_000, 40_000, 7))
    assert wanted <= set(got) and len(set(got)) == len(got) < len(wanted) + 80_000 / 10
    assert neardup._perhaps_among(docs, ids.limit(0)).count() == 0
