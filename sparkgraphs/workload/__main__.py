import json
import os
import sys

from pyspark.sql import SparkSession

from .experiments import X

name, sf_dir = sys.argv[1], sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.01"
spark = SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '4')}]").config("spark.sql.shuffle.partitions", "8").config("spark.sql.session.timeZone", "UTC").getOrCreate()
spark.sparkContext.setLogLevel("ERROR")
for row in X[name](spark, sf_dir):
    print(json.dumps(row, default=str))
spark.stop()
