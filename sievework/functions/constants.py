"""Fixed values of the method and of the stand-ins on the given tables."""

from __future__ import annotations

SCORES = ("writing", "coherence", "completeness", "logicality", "safety", "knowledge", "education", "helpfulness", "reasoning")
VALUE = ("knowledge", "education", "helpfulness", "reasoning")
PRESENTATION = ("writing", "coherence", "completeness", "logicality")
FOUR_POINT = tuple(s for s in SCORES if s != "safety")

#: Similarity bands: lower bound, weight; the top band is closed at 1, the others open above.
BANDS = ((0.99, 8), (0.98, 7), (0.96, 6), (0.95, 5), (0.94, 4), (0.92, 3), (0.90, 2))
TARGET = 10
HARD_THRESHOLD = 0.95
ALPHA = 0.6
VALUE_CUT = 1
POWER = {"n": 2.0, "k": 10.0, "a": 0.5}

#: Two-level tags of the sources; L2 is L1/source.
DOMAINS = {
    "src0": "Mathematics", "src1": "Science", "src2": "Physics", "src3": "Programming", "src4": "Computer Science",
    "src5": "Health", "src6": "Health", "src7": "Education", "src8": "Education", "src9": "Shopping",
    "src10": "Shopping", "src11": "Shopping", "src12": "Arts", "src13": "Arts", "src14": "Arts",
    "src15": "Arts", "src16": "Travel", "src17": "Sports", "src18": "Legal", "src19": "Finance",
}
BYPASS = ("Mathematics", "Science", "Physics", "Programming", "Computer Science")
DOMAIN_SETS = {"code": ("Programming", "Computer Science"), "math": ("Mathematics",), "stem": BYPASS}

#: English function words of the required-word rule.
REQUIRED = ("the", "be", "to", "of", "and", "that", "have", "with")
#: Function words of the four languages, for the signals.
FUNCTION_WORDS = ("the", "and", "of", "to", "der", "die", "das", "und", "de", "la", "le", "les", "et", "que", "el", "en", "los")
TOXIC = ("idiot", "clown", "moron", "pathetic", "trash", "loser", "stupid", "scum", "worthless", "disgusting")
BLOCKED_HOSTS = ("www.cheap-pills.example.com", "www.casino-win.example.org", "m.adult-x.example.net", "spam-farm.example.org")
BLOCKED_WORDS = ("casino", "pills", "adult", "free-bets")
