"""File-system metadata index and monitor on Spark: snapshots, summaries, change streams."""
