"""Readers and writers: state tables, contract files, source code, ledgers."""
