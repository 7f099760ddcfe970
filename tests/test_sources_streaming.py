import random
import time

from pyspark.sql import functions as F

from ctxloom.operators import adapt as A
from ctxloom.plans import streams as T
from ctxloom.sources import reads
from ctxloom.streaming import live


def test_fastq_splits_are_record_aligned(spark, tmp_path):
    r = random.Random(1)
    want = []
    with open(tmp_path / "a.fastq", "w") as f:
        for i in range(400):
            n = r.randint(1, 60)
            bases, quality = "".join(r.choice("ACGT") for _ in range(n)), "".join(r.choice("@+ABCI#") for _ in range(n))
            want.append((f"r{i}", bases, quality))
            f.write(f"@r{i} extra\n{bases}\n+\n{quality}\n")
    reads.register(spark)
    for split in (1 << 30, 997, 150):
        got = spark.read.format("fastq").option("split", str(split)).load(str(tmp_path / "a.fastq")).collect()
        assert sorted((x.read_id, x.bases, x.quality) for x in got) == sorted(want), split
    lines = reads.fastq_by_lines(spark, str(tmp_path / "a.fastq")).collect()
    assert sorted((x.read_id, x.bases, x.quality) for x in lines) == sorted(want)
    q = spark.createDataFrame([("!I", "aT")], "q string, b string").select(reads.quality_codes(F.col("q")).alias("q"), reads.base_codes(F.col("b")).alias("b")).first()
    assert q.q == [0, 40] and q.b == [0, 3]


def test_read_files_round_trip(spark, tmp_path):
    texts = [(1, "Ab, c1 é" * 30), (2, ""), (3, None), (4, "@+" * 60)]
    stream = T.text_stream(spark.createDataFrame(texts, "doc_id long, text string")).cut(101, "keep")
    reads.write_fastq(stream, str(tmp_path / "reads"))
    got = {r.read_id: r for r in reads.read_fastq(spark, str(tmp_path / "reads")).collect()}
    assert set(got) == {"1.0", "1.1", "1.2", "4.0", "4.1"} and [len(got[f"1.{i}"].bases) for i in range(3)] == [101, 101, 38]
    codes = {f"{r.doc_id}.{r.read_no}": r.syms for r in stream.frame().collect()}
    assert all([ord(c) - 33 for c in r.quality] == codes[k] for k, r in got.items())
    assert got["1.0"].bases[:8] == "ACTGCTGA"


def test_fasta_chunks_have_halos(spark, tmp_path):
    (tmp_path / "g.fa").write_text(">s1 x\nACGTAC\nGTA\n>s2\nGGG\n")
    reads.register(spark)
    got = spark.read.format("fasta").option("chunk", "4").option("halo", "2").load(str(tmp_path / "g.fa")).collect()
    assert [(x.seq_id, x.chunk_no, x.start, x.halo, x.bases) for x in got] == [("s1", 0, 0, "", "ACGT"), ("s1", 1, 4, "GT", "ACGT"), ("s1", 2, 8, "GT", "A"), ("s2", 0, 0, "", "GGG")]


def test_tables_have_versions(spark, tmp_path):
    for v in (1, 2):
        reads.save_table(spark.range(v), str(tmp_path), "bins", v)
    assert reads.load_table(spark, str(tmp_path), "bins").count() == 2 and reads.load_table(spark, str(tmp_path), "bins", 1).count() == 1
    spark.range(2).selectExpr("id", "'x' AS s").write.mode("overwrite").json(str(tmp_path / "j"))
    assert reads.json_lines(spark, str(tmp_path / "j"), "id long, s string").count() == 2
    spark.range(2).write.mode("overwrite").option("header", True).csv(str(tmp_path / "v"))
    assert reads.csv_rows(spark, str(tmp_path / "v"), "id long").agg(F.sum("id")).first()[0] == 1


def feed(spark, sf, tmp_path, files=4):
    events = spark.read.parquet(f"{sf}/events.parquet").orderBy("ts")
    folder = str(tmp_path / "feed")
    cuts = events.select(F.unix_micros(F.col("ts").cast("timestamp")).alias("t")).approxQuantile("t", [i / files for i in range(1, files)], 0.001)
    part = sum((F.unix_micros(F.col("ts").cast("timestamp")) >= int(c)).cast("int") for c in cuts)
    for i in range(files):  # one file after another: the stream takes them by age
        events.where(part == i).coalesce(1).write.mode("append").parquet(folder)
        time.sleep(0.05)
    return events, live.event_source(spark, folder, events.schema, delay="3650 days")


def test_live_counts_equal_batch(spark, sf, tmp_path):
    events, stream = feed(spark, sf, tmp_path)
    live.run_once(live.live_counts(stream, F.hour("ts"), T.ev_code()), "live_counts", "update", str(tmp_path / "c"))
    got = spark.sql("SELECT span, ctx, sym, max(n) AS n FROM live_counts GROUP BY span, ctx, sym")
    want = events.withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.window("ts", "1 day").alias("span"), F.hour("ts").alias("ctx"), T.ev_code().alias("sym")).count()
    assert got.agg(F.sum("n")).first()[0] == want.agg(F.sum("count")).first()[0] and got.count() == want.count()


def test_late_rows_are_dropped(spark, tmp_path):
    folder = str(tmp_path / "late")
    # a watermark counts against late rows from the batch after the next on
    for i, days in enumerate((["2024-01-01", "2024-01-10"], ["2024-01-10"], ["2024-01-02"], ["2024-01-09"])):
        spark.createDataFrame([(d, n + 10 * i) for n, d in enumerate(days)], "d string, event_id long").selectExpr("timestamp(d) AS ts", "event_id").coalesce(1).write.mode("append").parquet(folder)
        time.sleep(0.05)
    stream = live.event_source(spark, folder, spark.read.parquet(folder).schema, delay="3 days")
    live.run_once(live.live_counts(stream, F.lit(0), F.lit(0)), "late_counts", "update", str(tmp_path / "c"))
    days = {str(r.span.start)[:10] for r in spark.table("late_counts").collect()}
    assert "2024-01-09" in days and "2024-01-02" not in days


def test_adaptive_state_equals_batch(spark, sf, tmp_path):
    events, stream = feed(spark, sf, tmp_path)
    coded = stream.withColumn("sym", T.ev_code())
    live.run_once(live.adaptive_per_key(coded, "user_id", "ts", "sym", 5, 4), "adaptive", "update", str(tmp_path / "c"))
    got = {r.user_id: (r.n, round(r.bits, 6)) for r in spark.sql("SELECT user_id, max(struct(n, bits)) AS m FROM adaptive GROUP BY user_id").selectExpr("user_id", "m.n", "m.bits").collect()}
    want = {r.user_id: (r.n, round(r.b, 6)) for r in T.ev5(spark, sf).df.select("user_id", F.size("syms").alias("n"), A.cdf_bits(F.col("syms"), 5, 4).alias("b")).collect()}
    assert got == want


def test_drift_and_joins(spark, sf, tmp_path):
    events, stream = feed(spark, sf, tmp_path)
    model = spark.createDataFrame([(h, s, 2.5) for h in range(24) for s in range(5)], "ctx int, sym int, bits double")
    live.run_once(live.drift(stream, model, F.hour("ts"), T.ev_code()), "drift", "update", str(tmp_path / "d"))
    assert spark.table("drift").agg(F.max("bpv")).first()[0] == 2.5
    bins = spark.createDataFrame([(h, h // 6) for h in range(24)], "ctx int, bin int")
    live.run_once(live.with_bins(live.deduplicated(stream, "event_id"), F.hour("ts"), bins).select("event_id", "bin"), "binned", "append", str(tmp_path / "b"))
    assert spark.table("binned").count() == events.count()
    q = live.to_tables(live.live_counts(stream, F.lit(0), T.ev_code()), str(tmp_path / "t"), str(tmp_path / "tc"))
    q.awaitTermination()
    assert spark.read.parquet(str(tmp_path / "t")).count() > 0
