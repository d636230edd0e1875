"""Training-data operators: mixing, token output, dedup, classifiers, scans, rules, chat formatting.

Nothing outside this folder imports it.
"""
