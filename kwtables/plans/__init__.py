"""From words to a plan: parsing, rewrites, dispatch, SQL text."""
