"""Query text, plans and their rewrites."""
