"""Hand-made pages, page runs and speech with known results."""

from __future__ import annotations

from textquarry.operators import layout, speech


def boxes(spark, rows):
    return spark.createDataFrame([(p, b, *xy, (xy[2] - xy[0]) * (xy[3] - xy[1]), 1.0) for p, b, xy in rows], "page_id long, box_id int, x0 long, y0 long, x1 long, y1 long, inner long, conf double")


def test_suppression_and_page_flags(spark):
    nested = [(1, 1, (0, 0, 600, 400)), (1, 2, (10, 10, 50, 50)), (1, 3, (0, 400, 600, 800))]
    equal = [(2, 1, (0, 0, 600, 800)), (2, 2, (0, 0, 600, 800))]
    thin = [(3, 1, (0, 0, 100, 800))]
    title = [(4, 1, (0, 0, 600, 100))]
    crossing = [(5, 1, (0, 0, 400, 800)), (5, 2, (200, 0, 600, 800))]
    got = {r["page_id"]: r for r in layout.filter_pages(boxes(spark, nested + equal + thin + title + crossing)).collect()}
    assert (got[1]["n_boxes"], got[1]["flags"], got[1]["keep"]) == (2, [], True)
    assert (got[2]["n_boxes"], got[2]["flags"]) == (1, [])
    assert got[3]["flags"] == ["h_sparse"] and got[4]["flags"] == ["v_sparse"] and got[5]["flags"] == ["overlap"]


def test_greedy_suppression_ignores_suppressed_boxes(spark):
    # 2 lies in 1; 3 lies in 2 but not in 1: greedily it stays.
    rows = [(1, 1, (0, 0, 100, 100)), (1, 2, (20, 0, 110, 100)), (1, 3, (80, 0, 110, 100))]
    gone = {r["box_id"] for r in layout.suppress_greedy(boxes(spark, rows)).collect()}
    assert gone == {2}


def test_image_gate_modes(spark):
    rows = [(1, n, 0.9 if n <= 3 else 0.1, 220) for n in range(1, 15)] + [(2, n, 0.1, 150) for n in range(1, 12)]
    pages = spark.createDataFrame(rows, "pdf_id long, page_no int, area double, brightness long")
    assert {r["pdf_id"]: r["gate"] for r in layout.image_gate(pages).collect()} == {1: True, 2: False}
    worse = spark.createDataFrame([(1, n, 0.9 if n <= 8 else 0.1, 220) for n in range(1, 20)], "pdf_id long, page_no int, area double, brightness long")
    assert [r["gate"] for r in layout.image_gate(worse).collect()] == [False]
    assert [r["gate"] for r in layout.image_gate(worse, mode="any").collect()] == [True]


def test_page_runs_and_ocr(spark):
    pages = spark.createDataFrame([(7, n, f"t{n}") for n in (1, 2, 3, 5, 6, 9)], "pdf_id long, page_no int, text string")
    assert sorted((r["first_page"], r["text"]) for r in layout.merge_pages(pages).collect()) == [(1, "t1 t2 t3"), (5, "t5 t6"), (9, "t9")]
    json = '{"blocks":[{"box":[0,0,9,9],"paragraphs":[{"box":[0,0,5,5],"words":[{"text":"a","conf":0.5},{"text":"b","conf":1.0}]}]}]}'
    flat = layout.flatten_ocr(spark.createDataFrame([(1, json), (2, "{}"), (3, None)], "page_id long, json string")).collect()
    assert [(r["page_id"], r["text"]) for r in flat] == [(1, "a"), (1, "b"), (2, None), (3, None)]


def test_speech(spark):
    srt = "1\n00:00:01,000 --> 00:00:02,000\n[music] ANNA: well...\n\n2\n00:00:03,000 --> 00:00:04,000\n(laughs) yes\n"
    got = speech.srt_documents(spark.createDataFrame([(1, srt)], "file_id long, content string")).first()
    assert got["text"] == "ANNA: well\nyes"
    frames = spark.createDataFrame([(1, 0, 0, "so"), (1, 1, 100, "then"), (1, 2, 900, "go"), (1, 3, 5000, "end")], "video_id long, frame_id long, ms long, token string")
    parts = speech.transcribe(speech.segment_by_silence(frames, 500))
    assert speech.stitch(speech.punctuate(parts, 3000)).first()["text"] == "So then, go. End."
