"""kgtrail: question answering over knowledge graphs held as Spark DataFrames."""
