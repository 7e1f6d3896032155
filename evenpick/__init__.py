"""Fair center selection on Spark: nets, coresets, streaming summaries, baselines and measures."""

__version__ = "0.1.0"
