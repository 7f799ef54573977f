"""Goals, engine choice and plan inspection."""
