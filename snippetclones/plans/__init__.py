"""The query registry with its oracle SQL, and assertions on plans."""
