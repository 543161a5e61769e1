"""Plan-level helpers: staged tables, size checks and plan inspection."""
