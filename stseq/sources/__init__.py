"""Sources: adapters from tables, the planted-pattern generator, abnormal events, a Python data source."""
