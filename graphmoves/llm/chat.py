"""Chat formatting by a declarative template and a finite-state machine over roles; DataFrame functions only.

Control strings inside roles and texts are escaped reversibly: every backslash is doubled, then each
"<|" becomes "<\\|" (a single backslash between "<" and "|" can't arise otherwise), and a role's line
breaks become "<\\n|". Edge cases: null role or text is empty; rows of equal turn are ordered by role and
text; repeated rows are turns of their own; a null conv_id is one conversation; an empty table gives no rows.
A conversation is one value of its output, so it has to fit a row, whatever its number of turns.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TEMPLATE = {
    "open": "<|im_start|>",
    "role_end": "\n",
    "close": "<|im_end|>\n",
    "loss_roles": ["assistant"],
    # state -> role -> next state; a role that a state doesn't list is out of order
    "machine": {
        "start": {"system": "told", "user": "asked"},
        "told": {"user": "asked"},
        "asked": {"assistant": "answered"},
        "answered": {"user": "asked"},
    },
    "final": ["answered"],
}


def escape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("<\\|"), F.lit("<|")), F.lit("\\\\"), F.lit("\\"))


def escape_role(role: Column) -> Column:
    return F.replace(escape(role), F.lit("\n"), F.lit("<\\n|"))


def unescape_role(role: Column) -> Column:
    return unescape(F.replace(role, F.lit("<\\n|"), F.lit("\n")))


def run_machine(roles: Column, template: dict) -> Column:
    """State after all turns; "bad:<n>" names the first turn out of order, from 0."""
    moves = F.create_map(*[F.lit(x) for s, to in template["machine"].items() for r, t in to.items() for x in (f"{s}\x00{r}", t)])
    seen = F.aggregate(
        roles, F.struct(F.lit("start").alias("s"), F.lit(0).alias("n")),
        lambda a, r: F.struct(
            F.when(a["s"].startswith("bad:"), a["s"])
            .otherwise(F.coalesce(F.try_element_at(moves, F.concat(a["s"], F.lit("\x00"), r)), F.concat(F.lit("bad:"), a["n"].cast("string")))).alias("s"),
            (a["n"] + 1).alias("n")))
    return seen["s"]


def format_chats(conversations: DataFrame, template: dict | None = None) -> DataFrame:
    """One row per conversation: conv_id, segments array<struct<text, loss>>, formatted, state, valid."""
    t = template or TEMPLATE
    role, text = F.coalesce("role", F.lit("")), F.coalesce("text", F.lit(""))
    turns = conversations.groupBy("conv_id").agg(
        F.sort_array(F.collect_list(F.struct(F.col("turn").alias("turn"), role.alias("role"), text.alias("text")))).alias("_turns"))
    plain = lambda x: F.struct(x.alias("text"), F.lit(False).alias("loss"))
    segments = F.flatten(F.transform("_turns", lambda x: F.array(
        plain(F.concat(F.lit(t["open"]), escape_role(x["role"]), F.lit(t["role_end"]))),
        F.struct(escape(x["text"]).alias("text"), x["role"].isin(t["loss_roles"]).alias("loss")),
        plain(F.lit(t["close"])))))
    out = turns.select("conv_id", segments.alias("segments"), run_machine(F.transform("_turns", lambda x: x["role"]), t).alias("state"))
    return out.select("conv_id", "segments", F.array_join(F.transform("segments", lambda s: s["text"]), "").alias("formatted"),
                      "state", F.col("state").isin(t["final"]).alias("valid"))


def parse_chat(formatted: Column, template: dict | None = None) -> Column:
    """array<struct<role, text>> read back from a formatted conversation."""
    t = template or TEMPLATE
    pieces = F.filter(F.split(formatted, r"\Q" + t["open"] + r"\E"), lambda p: p != "")

    def read(p):
        role = F.substring_index(p, t["role_end"], 1)
        at = F.length(role) + len(t["role_end"]) + 1
        body = F.substring(p, at, F.length(p) - at + 1 - len(t["close"]))
        return F.struct(unescape_role(role).alias("role"), unescape(body).alias("text"))

    return F.transform(pieces, read)


def loss_text(segments: Column) -> Column:
    return F.array_join(F.transform(F.filter(segments, lambda s: s["loss"]), lambda s: unescape(s["text"])), "")


def chat_digest(chats: DataFrame) -> DataFrame:
    """The digest of each formatted conversation, from what is read back."""
    turns = parse_chat(F.col("formatted"))
    read = chats.select("conv_id", "formatted", "valid", turns.alias("_turns"), loss_text(F.col("segments")).alias("_loss"))
    told = F.array_join(F.transform("_turns", lambda x: F.concat(x["role"], F.lit("\n"), x["text"], F.lit("\n"))), "")
    return read.select("conv_id", F.size("_turns").cast("long").alias("n_turns"), F.sha2(F.encode(told, "utf-8"), 256).alias("turns_sha256"),
                       F.length("_loss").cast("long").alias("loss_chars"), F.sha2(F.encode("_loss", "utf-8"), 256).alias("loss_sha256"),
                       F.length("formatted").cast("long").alias("formatted_chars"), "valid")
