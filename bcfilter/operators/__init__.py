"""Filter building, probing, clearing, measures, baselines, traces and relational helpers."""
