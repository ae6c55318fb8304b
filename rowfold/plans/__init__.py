"""Plan building and inspection."""
