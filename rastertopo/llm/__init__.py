"""Operators that prepare training text at corpus scale; nothing else imports this subpackage."""
