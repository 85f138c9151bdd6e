"""A process for one pipeline: its specification on standard input, a trial as JSON on standard output."""

from __future__ import annotations

import json
import sys

from ..session import session
from .executor import run_spec

if __name__ == "__main__":
    spark = session(int(sys.argv[2]), sys.argv[3])
    spark.sparkContext.setLogLevel("ERROR")
    print(json.dumps(run_spec(spark, sys.argv[1], sys.stdin.read())))
    spark.stop()
