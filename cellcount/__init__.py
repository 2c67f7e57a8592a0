"""cellcount: answer large batches of exact counting queries on Spark in far less work than one by one."""
