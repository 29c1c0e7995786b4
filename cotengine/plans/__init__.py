"""Composed plans (curation, failure rounds) and the catalogue of registered queries."""
