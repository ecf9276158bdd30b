"""Training-data operators: licence, quality, mixing, near-duplicate, chat, token and toxicity work.

Nothing outside this subpackage imports it; ``registry`` holds its queries and their SQL.
"""
