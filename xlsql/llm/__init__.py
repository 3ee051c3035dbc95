"""Operators for preparing training data: near duplicates, archives, tokens, filters. Nothing else imports this subpackage."""
