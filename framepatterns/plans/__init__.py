"""Run-time choices: cardinality, patterns by measured sizes, cost predictions, explain."""
