"""DataFrame operators: nets, coresets, distributed and one-pass methods, baselines, measures, joins, reports."""
