"""Candidate patterns: every generator ends in a ``Pool``; selectors don't know where patterns come from."""
