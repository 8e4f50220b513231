"""Factored linear algebra over normalized tables, as DataFrame plans."""
