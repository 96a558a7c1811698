"""Sampling, tasks, queues, classifiers and measures, each a DataFrame-to-DataFrame function."""
