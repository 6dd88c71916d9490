"""Printers of plain SQL for checking: nothing here uses the compiler."""
