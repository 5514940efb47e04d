"""Evaluation on DataFrames: path reach and traces, verdicts, evidence, validation, patterns, audits."""
