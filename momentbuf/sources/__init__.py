"""Indexed arrays: making, checking, generating, writing and reading them."""
