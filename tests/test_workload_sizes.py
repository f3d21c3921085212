from proxigraph.plans import workloads


def test_sizes_end_with_the_whole_tables(spark, small_dir):
    steps = workloads._sizes(spark, small_dir)
    for name, table in (("num", "lineitem"), ("doc", "documents")):
        n = spark.read.parquet(f"{small_dir}/{table}.parquet").count()
        own = [s for s in steps if s[0] == name]
        assert own[-1][1] == n and own[-1][2].df.count() + own[-1][3].df.count() == n and own[0][1] < n
