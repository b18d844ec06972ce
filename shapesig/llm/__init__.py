"""Training-data operators: near and exact dedup, formatting, extraction, scoring, mixing.

Nothing outside this subpackage imports it; ``entries`` holds its queries and SQL.
"""
